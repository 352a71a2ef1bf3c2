"""Information-theoretic removal of personal data.

Protected entities (addresses, numbers and secrets that the patterns below describe) are
replaced by the name of their class. Other terms can still give an entity away: where a
term occurs, how much of the entity's information does it carry? Contexts are the distinct
lines of the corpus; with n(e), n(t) and n(t,e) the contexts that hold entity, term and
both, of N in all, the disclosure of e by t is

    log2(n(t,e) N / (n(t) n(e))) / log2(N / n(e)),

the point-wise mutual information as a share of what there is to learn about e. A term
seen with e in at least `MIN_SUPPORT` independent contexts whose disclosure reaches
`DISCLOSURE` is generalised wherever it stands: a capitalised word to <NAME>, any other to
<TERM>.

All counts are over the whole corpus. A line that is repeated is one context, and edited
copies of a line are one as well: n(e), n(t) and n(t,e) count groups of lines. A line joins
the first group, in the order of the lines' hashes, whose first line it copies, which is
when both hold the same numbers and their words, without the entities and the term in
question, have a Jaccard similarity of at least `NEAR`; so a form filled in with other
numbers is no copy. N is the number of distinct lines, counted by their 64-bit hashes. n(t)
takes the lines with entities first, so that their groups alone bound it from below: only terms that can still pass are
looked for in the other lines, and counting stops where no entity's threshold can be
reached. The documents that hold revealing terms are joined back by broadcast while their
list is under `BROADCAST_BYTES`, else by a shuffle.

Defined results: null and empty texts stay as they are; without entities nothing changes;
terms are runs of at least `MIN_TERM` letters, compared in lower case; rows of equal
doc_id and text are treated alike; ties don't matter, as every term over the threshold
goes; an entity found inside another (an address within a secret) counts with it, once;
columns beyond `doc_id` and `text` are ignored.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import cut

MIN_SUPPORT = 3
DISCLOSURE = 0.95
NEAR = 0.8
MIN_TERM = 1
BROADCAST_BYTES = 32 << 20

#: Class and pattern, in the order in which they are replaced.
PATTERNS = (
    ("SECRET", r"-----BEGIN [A-Z ]*PRIVATE KEY-----[\s\S]*?(?:-----END [A-Z ]*PRIVATE KEY-----|\z)"),
    ("SECRET", r"""(?i)\b(?:token|secret|passwd|password|api[_-]?key|access[_-]?key|auth[_-]?key)\b["']?\s*[:=]\s*(?:"[^"\n]{6,}"|'[^'\n]{6,}'|[^\s"']{8,})"""),
    ("SECRET", r"\b(?:AKIA[0-9A-Z]{16}|gh[pousr]_[A-Za-z0-9]{30,}|sk-[A-Za-z0-9_-]{20,}|xox[abprs]-[A-Za-z0-9-]{10,}|eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{5,})"),
    ("EMAIL", r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]++(?:\.[\p{L}\p{N}-]++)*\.\p{L}{2,}|(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]++(?:\.[\p{L}\p{N}-]+)+"),
    ("IBAN", r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?\b"),
    ("IP", r"(?<![\d.])(?:\d{1,3}\.){3}\d{1,3}(?!\d|\.\d)"),
    ("IP", r"(?i)(?<![0-9a-f:])(?:[0-9a-f]{1,4}:){7}[0-9a-f]{1,4}(?![0-9a-f:])"),
    ("CARD", r"(?<![\d.])(?:\d[ -]?){12,18}\d(?!\d)"),
    ("SSN", r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])"),
    ("PHONE", r"(?<![\d\p{L}])(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}(?!\d)"),
    ("PHONE", r"(?<![\d\p{L}])\+\d(?:[ .-]?\d){7,14}(?!\d)"),
    ("PHONE", r"(?<![\d\p{L}.-])\d{3}[ .-]\d{3}[ .-]\d{4}(?![\d-])"),
)
#: What any of the patterns needs; most documents have none of it.
_HINT = r"[0-9@=]|(?i:secret|passw|token|(?:api|access|auth)[_-]?key)|-----BEGIN|AKIA|gh[pousr]_|sk-|xox[abprs]-|eyJ|(?i:[a-f]:[a-f]{1,4}:)"
_TERM = r"\p{L}{%d,}" % MIN_TERM
#: Strings of which one is in whatever a pattern finds without a digit, @ or =. All are looked for as they are, and the slower search for hints begins only where one is found.
_SIGNS = (":", "-----BEGIN", "AKIA", "_", "sk-", "xox", "eyJ")


def hinted(text: Column) -> Column:
    """Whether any pattern can find something: true of every text with an entity, and of few others."""
    sign = F.lit(False)
    for x in _SIGNS:
        sign = sign | text.contains(x)
    return text.rlike("[0-9@=]") | (sign & text.rlike(_HINT))


def masked(text: Column) -> Column:
    out = text
    for name, pattern in PATTERNS:
        out = F.regexp_replace(out, pattern, f"<{name}>")
    return F.when(hinted(text), out).otherwise(text)


def _n_entities(text: Column, clean: Column) -> Column:
    """Entities that `clean` names and `text` did not: one found inside another counts with it, once."""
    marks = F.lit("<(?:" + "|".join(sorted({name for name, _ in PATTERNS})) + ")>")
    return F.when(clean == text, 0).otherwise(F.coalesce(F.regexp_count(clean, marks) - F.regexp_count(text, marks), F.lit(0)))


def _entities(text: Column) -> Column:
    """All entities of a text, each found after those of the patterns before it were masked."""
    found, rest = [], text
    for name, pattern in PATTERNS:
        found.append(F.regexp_extract_all(rest, F.lit(pattern), F.lit(0)))
        rest = F.regexp_replace(rest, pattern, f"<{name}>")
    return F.array_distinct(F.flatten(F.array(*found)))


def _terms(text: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(_TERM), F.lit(0)))


def _words(bare: Column) -> Column:
    """The sorted hashes of a line's words."""
    return F.array_sort(F.array_distinct(F.transform(F.regexp_extract_all(F.lower(bare), F.lit(r"\p{L}+"), F.lit(0)), lambda x: F.xxhash64(x))))


def _numbers(line: Column) -> Column:
    return F.xxhash64(F.array_sort(F.array_distinct(F.regexp_extract_all(line, F.lit(r"\p{Nd}+"), F.lit(0)))))


class _Groups:
    """Groups of near copies, in the order in which lines are added."""

    def __init__(self) -> None:
        self.first: list[set] = []
        self.index: dict = defaultdict(list)

    def add(self, words, numbers: int) -> int:
        """The number of the line's group. Similar sets share one of their first words in sorted order."""
        own = [int(x) for x in words]
        size, mine = len(own), set(own)
        keys = [(numbers, x) for x in own[: size - -(-size * round(NEAR * 100) // 100) + 1]] or [(numbers, None)]
        for g in sorted({g for k in keys for g in self.index[k]}):
            both = len(mine & self.first[g])
            # the term in question is in both
            if 100 * max(both - 1, 0) >= round(NEAR * 100) * max(size + len(self.first[g]) - both - 1, 0):
                return g
        for k in keys:
            self.index[k].append(len(self.first))
        self.first.append(mine)
        return len(self.first) - 1


def _grouped(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Rows sorted by (entity, numbers, context), each with its group among those of the entity and the numbers."""
    last, groups = None, _Groups()
    for b in batches:
        found = []
        for e, numbers, words in zip(b["entity"], b["numbers"], b["words"]):
            if (e, numbers) != last:
                last, groups = (e, numbers), _Groups()
            found.append(groups.add(words, numbers))
        yield b[["entity", "numbers", "t"]].assign(g=found)


def _counted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """(term, n_t) of rows sorted by (term, later, context): the number of groups, or the first beyond the term's limit."""
    last, limit, groups = None, 0, _Groups()
    for b in batches:
        found = []
        for term, most, numbers, words in zip(b["term"], b["most"], b["numbers"], b["words"]):
            if term != last:
                if last is not None:
                    found.append((last, len(groups.first)))
                last, limit, groups = term, most, _Groups()
            if len(groups.first) <= limit:
                groups.add(words, numbers)
        yield pd.DataFrame(found, columns=["term", "n_t"])
    if last is not None:
        yield pd.DataFrame([(last, len(groups.first))], columns=["term", "n_t"])


def _n_t(lines: DataFrame) -> DataFrame:
    return lines.repartition("term").sortWithinPartitions("term", "later", "context").select("term", "most", "numbers", "words").mapInPandas(_counted, "term string, n_t long")


def revealing(docs: DataFrame, min_support: int = MIN_SUPPORT, disclosure: float = DISCLOSURE) -> tuple[DataFrame, DataFrame] | None:
    """(terms with the entities they disclose, (doc_id, fp, term) places of candidate terms), or None without a candidate.

    Terms: (term, entity, n_te, n_t, n_e, disclosure).
    """
    text = F.col("text")
    keyed = docs.where(text.isNotNull()).select("doc_id", F.xxhash64("text").alias("fp"), "text")
    lines = keyed.where(hinted(text)).select(F.explode_outer(F.split("text", "\n", -1)).alias("line")).where(hinted(F.col("line")))
    bare = F.regexp_replace(masked(F.col("line")), "<[A-Z]+>", " ")
    held = lines.select(F.xxhash64("line").alias("context"), _entities(F.col("line")).alias("e"), _terms(bare).alias("t"), _words(bare).alias("words"), _numbers(F.col("line")).alias("numbers")).where(F.size("e") > 0).dropDuplicates(["context"])
    held = cut(held, "entities")
    each = held.select("context", "t", "words", "numbers", F.explode("e").alias("entity"))
    # an entity seen in too few lines can't pass the support test with any term
    often = each.groupBy("entity").agg(F.count("*").alias("n")).where(F.col("n") >= min_support).select("entity")
    each = each.join(often, "entity").repartition("entity", "numbers").sortWithinPartitions("entity", "numbers", "context").select("entity", "numbers", "t", "words")
    groups = cut(each.mapInPandas(_grouped, "entity string, numbers long, t array<string>, g int"), "groups")
    n_e = groups.groupBy("entity").agg(F.count_distinct("numbers", "g").alias("n_e")).where(F.col("n_e") >= min_support)
    n_te = groups.select("entity", "numbers", "g", F.explode("t").alias("term")).groupBy("entity", "term").agg(F.count_distinct("numbers", "g").alias("n_te")).where(F.col("n_te") >= min_support)
    n = keyed.select(F.explode_outer(F.split("text", "\n", -1)).alias("line")).select(F.xxhash64("line").alias("context")).distinct().count()

    def share(n_t):
        return F.log2(F.col("n_te") * F.lit(float(n)) / (F.greatest(n_t, F.col("n_te")) * F.col("n_e"))) / F.log2(F.lit(float(n)) / F.col("n_e"))

    pairs = cut(n_te.join(n_e, "entity").where(F.col("n_e") < n).where(share(F.lit(0)) >= disclosure), "pairs")
    # with more groups than this a term reaches the threshold with no entity
    most = pairs.groupBy("term").agg(F.ceil(F.max(F.col("n_te") * F.pow(F.lit(float(n)) / F.col("n_e"), 1 - disclosure)) + 1).cast("long").alias("most"))
    beside = cut(held.select("context", "words", "numbers", F.explode("t").alias("term"), F.lit(0).alias("later")).join(most, "term"), "beside")
    # a term has at least the groups it has beside entities; if that already makes it too common, no more counting can help
    pairs = cut(pairs.join(_n_t(beside).withColumnRenamed("n_t", "n_min"), "term").where(share(F.col("n_min")) >= disclosure), "pairs")
    terms = pairs.select("term").distinct()
    if terms.isEmpty():
        return None
    words = keyed.select("doc_id", "fp", F.explode_outer(F.split("text", "\n", -1)).alias("line")).select("doc_id", "fp", "line", F.explode_outer(_terms(F.col("line"))).alias("term"))
    places = cut(words.join(terms, "term").select("doc_id", "fp", "term", F.xxhash64("line").alias("context"), _words(F.col("line")).alias("words"), _numbers(F.col("line")).alias("numbers")), "places")
    others = places.select("context", "words", "numbers", "term", F.lit(1).alias("later")).dropDuplicates(["term", "context"]).join(held.select("context"), "context", "left_anti").join(most, "term")
    n_t = _n_t(beside.join(terms, "term").unionByName(others))
    found = pairs.join(n_t, "term").select("term", "entity", "n_te", "n_t", "n_e", share(F.col("n_t")).alias("disclosure")).where(F.col("disclosure") >= disclosure)
    return found, places.select("doc_id", "fp", "term").distinct()


def sanitise(docs: DataFrame, min_support: int = MIN_SUPPORT, disclosure: float = DISCLOSURE) -> DataFrame:
    """(doc_id, text, n_entities, n_terms): the sanitised texts and how many entities and distinct terms of each were generalised."""
    text = F.col("text")
    base = docs.select("doc_id", F.xxhash64("text").alias("__fp"), "text")
    got = revealing(docs, min_support, disclosure)
    clean = masked(text)
    if got is None:
        out = base.select("doc_id", clean.alias("__c"), text)
        return out.select("doc_id", F.col("__c").alias("text"), _n_entities(text, F.col("__c")).alias("n_entities"), F.lit(0).alias("n_terms"))
    found, places = got
    hits = cut(places.join(found.select("term").distinct(), "term").groupBy("doc_id", "fp").agg(F.array_sort(F.collect_set("term")).alias("__terms")).select(F.col("doc_id").alias("__id"), F.col("fp").alias("__f"), "__terms"), "hits")
    size = hits.agg(F.sum(F.size("__terms") * 24 + 32)).first()[0] or 0
    side = F.broadcast(hits) if size <= BROADCAST_BYTES else hits
    out = base.join(side, base["doc_id"].eqNullSafe(F.col("__id")) & (F.col("__fp") == F.col("__f")), "left").select("doc_id", clean.alias("__c"), text, "__terms")
    out = out.select("doc_id", "__c", _n_entities(text, F.col("__c")).alias("n_entities"), "__terms")
    # split before and after every run of letters, so that terms are compared as whole words
    parts = F.split("__c", r"(?<=\p{L})(?!\p{L})|(?<!\p{L})(?=\p{L})", -1)
    word = F.transform(parts, lambda w: F.when(F.array_contains("__terms", F.lower(w)), F.when(w.rlike(r"^\p{Lu}"), "<NAME>").otherwise("<TERM>")).otherwise(w))
    return out.select("doc_id", F.when(F.col("__terms").isNull(), F.col("__c")).otherwise(F.array_join(word, "")).alias("text"), "n_entities", F.coalesce(F.size("__terms"), F.lit(0)).alias("n_terms"))


def op10_sanitise(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sanitise(spark.read.parquet(f"{sf_dir}/documents.parquet"))
