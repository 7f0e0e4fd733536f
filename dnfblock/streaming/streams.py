"""Learned schemes on streams: static index, two streams, late data, a stateful index, growing tables."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from dnfblock.operators.blocking import index
from dnfblock.operators.scheme import Scheme

MOST_PAIRS = 100_000  # pairs that are handed on at once


def stream_candidates_static(stream: DataFrame, static: DataFrame, scheme: Scheme) -> DataFrame:
    """New left records against a static right side: stateless, keys are made in the stream's plan.

    A pair shows once per key that it shares; ``dropDuplicates`` within a batch or downstream.
    """
    arriving = index(stream, scheme, 0).select("term_id", "key", F.col("rid").alias("l_rid"))
    known = index(static, scheme, 1).select("term_id", "key", F.col("rid").alias("r_rid"))
    return arriving.join(known, ["term_id", "key"]).select("l_rid", "r_rid", "term_id", "key")


def stream_stream_candidates(left: DataFrame, right: DataFrame, key: str, time: str, wait: str = "1 hour") -> DataFrame:
    """Both sides arrive: pairs of equal ``key`` whose ``time`` differs by at most ``wait``.

    Watermarks on both sides let Spark drop what no later record can meet.
    """
    l = left.withWatermark(time, wait).select(F.col("rid").alias("l_rid"), F.col(key).alias("lk"), F.col(time).alias("lt"))  # noqa: E741
    r = right.withWatermark(time, wait).select(F.col("rid").alias("r_rid"), F.col(key).alias("rk"), F.col(time).alias("rt"))
    near = F.expr(f"lk = rk AND rt BETWEEN lt - INTERVAL {wait} AND lt + INTERVAL {wait}")
    return l.join(r, near).select("l_rid", "r_rid", "lt", "rt")


def without_redelivery(stream: DataFrame, time: str = "ts", id_col: str = "rid", late: str = "10 minutes") -> DataFrame:
    """Records that are delivered again within the watermark are dropped."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark([id_col])


def block_growth(events: DataFrame, key: str, time: str = "ts", size: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Records per block and tumbling or sliding window; works on tables and, with a watermark, on streams."""
    window = F.window(time, size, slide) if slide else F.window(time, size)
    rows = events.groupBy(window.alias("w"), F.col(key).alias("key")).agg(F.count("*").alias("n"))
    return rows.select(F.col("w.start").alias("window_start"), "key", "n")


def block_sessions(events: DataFrame, key: str, time: str = "ts", gap: str = "30 minutes") -> DataFrame:
    """Records per block and session: a gap without records ends one."""
    rows = events.groupBy(F.session_window(time, gap).alias("w"), F.col(key).alias("key")).agg(F.count("*").alias("n"))
    return rows.select(F.col("w.start").alias("window_start"), "key", "n")


class PairingIndex(StatefulProcessor):
    """Per key, the records of either side so far; a new record meets those of the other side.

    State holds every record, and forgets after ``ttl_ms`` only.
    """

    def __init__(self, ttl_ms: int = 86_400_000):
        self.ttl = ttl_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.sides = [handle.getListState(f"side{s}", "rid string", ttlDurationMs=self.ttl) for s in (0, 1)]

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        held = [[r[0] for r in s.get()] for s in self.sides]
        known = [set(ids) for ids in held]
        for frame in rows:
            out: list[tuple[str, str]] = []
            for side, rid in zip(frame["side"], frame["rid"]):
                if rid in known[side]:
                    continue
                out += [(rid, o) if side == 0 else (o, rid) for o in held[1 - side]]
                known[side].add(rid)
                held[side].append(rid)
                if len(out) >= MOST_PAIRS:
                    yield pd.DataFrame(out, columns=["l_rid", "r_rid"])
                    out = []
            yield pd.DataFrame(out, columns=["l_rid", "r_rid"])
        for state, ids in zip(self.sides, held):
            if ids:
                state.put([(r,) for r in ids])

    def close(self) -> None:
        pass


def stateful_candidates(keys: DataFrame, ttl_ms: int = 86_400_000) -> DataFrame:
    """``l_rid, r_rid`` from a stream of ``key, side, rid``; needs the RocksDB state store provider."""
    return keys.groupBy("key").transformWithStateInPandas(
        PairingIndex(ttl_ms), outputStructType="l_rid string, r_rid string", outputMode="Append", timeMode="ProcessingTime"
    )


def merge_property_table(table: DataFrame, batch: DataFrame) -> DataFrame:
    """A long property table (``s, p, values``) after a batch of triples; for ``foreachBatch``."""
    new = batch.groupBy("s", "p").agg(F.collect_set("o").alias("fresh"))
    rows = table.join(new, ["s", "p"], "full")
    none = F.array().cast("array<string>")
    both = F.array_union(F.coalesce("values", none), F.coalesce("fresh", none))
    return rows.select("s", "p", F.array_sort(both).alias("values"))
