"""Blocking of streams: the same expressions, with bounded state where state is needed."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import StructType

from ..model import Attribute, BlockingSpec, BlockTree
from ..operators.assign import with_block_key

EVENT_SPEC = BlockingSpec(
    "event_id",
    (
        Attribute("hour", "code", "date_format(ts, 'yyyy-MM-dd HH')", "strftime(ts, '%Y-%m-%d %H')"),
        Attribute("k", "code", "get_json_object(props, '$.k')", "json_extract_string(props, '$.k')"),
        Attribute("type", "code", "event_type"),
        Attribute("user", "int", "user_id"),
    ),
)


def stream(spark: SparkSession, folder: str, schema: StructType | str, files_per_trigger: int = 1) -> DataFrame:
    """A file stream of Parquet."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def assign(events: DataFrame, tree: BlockTree, spec: BlockingSpec) -> DataFrame:
    """`events` with their block; stateless, the same for batch and stream (routing by broadcast join included)."""
    return with_block_key(events, tree, spec)


def block_counts(blocked: DataFrame, ts: str = "ts", every: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(block_key, start, n) in event-time windows. A timestamp without zone is taken in the session's zone, as watermarks need one with."""
    x = blocked.withColumn("__ts", F.col(ts).cast("timestamp"))
    x = x.withWatermark("__ts", late) if blocked.isStreaming else x
    w = F.window("__ts", every, slide) if slide else F.window("__ts", every)
    return x.groupBy("block_key", w.alias("w")).agg(F.count("*").alias("n")).select("block_key", F.col("w.start").alias("start"), "n")


def session_blocks(blocked: DataFrame, ts: str = "ts", gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(block_key, start, n) of runs of events of a block without a longer gap."""
    x = blocked.withColumn("__ts", F.col(ts).cast("timestamp"))
    x = x.withWatermark("__ts", late) if blocked.isStreaming else x
    return x.groupBy("block_key", F.session_window("__ts", gap).alias("w")).agg(F.count("*").alias("n")).select("block_key", F.col("w.start").alias("start"), "n")


def drop_copies(events: DataFrame, keys: list[str], ts: str = "ts", late: str = "10 minutes") -> DataFrame:
    """Events without exact copies that arrive within the watermark."""
    x = events.withColumn("__ts", F.col(ts).cast("timestamp"))
    return x.withWatermark("__ts", late).dropDuplicatesWithinWatermark(keys) if events.isStreaming else x.dropDuplicates(keys)


class _Match(StatefulProcessor):
    """Pairs every arriving record with the last `cap` records of its block; older state falls out."""

    def __init__(self, cap: int, ttl_ms: int):
        self.cap, self.ttl = cap, ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.seen = handle.getListState("seen", "id bigint", ttlDurationMs=self.ttl)

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timer_values: Any) -> Iterator[pd.DataFrame]:
        held = [r[0] for r in self.seen.get()]
        out = []
        for pdf in rows:
            for i in sorted(pdf["id"].tolist()):
                out += [(key[0], min(i, j), max(i, j)) for j in held if i != j]
                held = [*held, i][-self.cap :]
        self.seen.put([(i,) for i in held])
        yield pd.DataFrame(out, columns=["block_key", "l_id", "r_id"])

    def close(self) -> None:
        pass


def match_stream(blocked: DataFrame, id_col: str, cap: int, ttl_ms: int = 3_600_000) -> DataFrame:
    """(block_key, l_id, r_id) candidate pairs of a stream, with state of at most `cap` ids a block. Needs the RocksDB state store."""
    return blocked.select(F.col(id_col).cast("bigint").alias("id"), "block_key").groupBy("block_key").transformWithStateInPandas(_Match(cap, ttl_ms), "block_key string, l_id bigint, r_id bigint", "Append", "None")


def monitor(blocked: DataFrame, cap: int, on_overflow: Callable[[DataFrame, int], None], checkpoint: str):
    """Start a query that calls on_overflow(blocks over the cap, batch) for micro-batches with such blocks, so that the tree can be cut anew."""

    def each(batch: DataFrame, number: int) -> None:
        over = batch.groupBy("block_key").agg(F.count("*").alias("n")).where(F.col("n") > cap)
        if not over.isEmpty():
            on_overflow(over, number)

    return blocked.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
