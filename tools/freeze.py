"""Learn the plans that the assignment queries and their SQL share, on the sf0.01 tables, and write them to blockwright/plans/frozen.json."""

import json
import sys
from pathlib import Path

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

from pyspark.sql import SparkSession

from blockwright import workloads as w
from blockwright.functions.hashes import default_library
from blockwright.model import BlockingConfig
from blockwright.operators import learn, sizes

CAP = 50


def main(folder: str) -> None:
    spark = SparkSession.builder.master("local[4]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "8").getOrCreate()
    docs = w.table(spark, folder, "documents")
    library = default_library(w.DOC_SPEC, without=("longest_token",))
    f = sizes.features(docs, w.DOC_SPEC, w.doc_pairs(docs), library, cap=10)
    config = BlockingConfig(CAP, scorer="optimistic", min_shrink=0.5)
    out = {name: learner(f, config).to_json() for name, learner in learn.LEARNERS.items()}
    # a cap that the single function and the chain can't keep, so that random splits are in the plans too
    small = BlockingConfig(10, scorer="optimistic", min_shrink=0.5)
    out |= {f"{name}_small": learner(f, small).to_json() for name, learner in learn.LEARNERS.items()}
    out["rounds"] = learn.learn_rounds(f, small, "level_tree").to_json()
    fine = learn.learn_block_tree(f, BlockingConfig(10, scorer="optimistic"))
    out["fine"] = fine.to_json()
    Path(__file__).resolve().parents[1].joinpath("blockwright/plans/frozen.json").write_text(json.dumps(out, ensure_ascii=False, indent=0))
    for k, v in out.items():
        print(k, len(v))


if __name__ == "__main__":
    main(sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01")
