"""Queries of the training-text operators, and their SQL where SQL can express them."""

from . import compression_classifier, language_id, line_dedup, mixing, near_dedup, packing, quality_rules, sanitise, vantage, warc

QUERIES = {
    f.__name__: f
    for f in (
        mixing.op1_mixing,
        compression_classifier.op2_compression_classifier,
        line_dedup.op3_line_dedup,
        language_id.op4_language_id,
        warc.op5_warc_normaliser,
        packing.op6_best_fit_packing,
        quality_rules.op7_quality_rules,
        vantage.op8_vantage_points,
        near_dedup.op9_near_dedup,
        sanitise.op10_sanitise,
    )
}

ORACLES: dict[str, str] = {
    "op1_mixing": mixing.OP1_SQL,
    "op3_line_dedup": line_dedup.OP3_SQL,
    "op5_warc_normaliser": warc.OP5_SQL,
    "op8_vantage_points": vantage.OP8_SQL,
}
