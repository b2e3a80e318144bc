"""Streaming: file-stream sources, late data, and the count-based window's exact top-m in state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

TOPM = "win long, pos int, oid long, num long"
STATE = "seen long, seqs array<long>, oids array<array<long>>, nums array<array<long>>"


def source(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.readStream.schema(schema).parquet(path)


def on_time(stream: DataFrame, delay: str = "10 minutes", key: str = "seq") -> DataFrame:
    """Late rows beyond the watermark go; repeated queries within it go too."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def count_window_topm(stream: DataFrame, w: int, m: int) -> DataFrame:
    """stream: monitor, seq, oids, nums. Keeps the last w queries of each monitor in state and emits m rows for every full window.

    Within a micro-batch queries are taken by seq, so cuts into batches don't change the output.
    """

    def run(key, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen, seqs, oids, nums = state.get if state.exists else (0, [], [], [])
        live = list(zip(seqs, oids, nums))
        new = pd.concat(list(batches)).sort_values("seq")
        total: dict[int, int] = {}
        touch: dict[int, int] = {}

        def put(q, sign: int) -> None:
            for o, c in zip(q[1], q[2]):
                total[o] = total.get(o, 0) + sign * int(c)
                touch[o] = touch.get(o, 0) + sign

        for q in live:
            put(q, 1)
        rows = []
        for seq, o, c in zip(new.seq, new.oids, new.nums):
            q = (int(seq), [int(x) for x in o], [int(x) for x in c])
            live.append(q)
            put(q, 1)
            if len(live) > w:
                put(live.pop(0), -1)
            if len(live) == w:
                best = sorted((o for o in total if touch[o]), key=lambda o: (-total[o], o))[:m]
                rows += [(int(seq), i, o, total[o]) for i, o in enumerate(best, 1)]
        state.update((seen + len(new), [q[0] for q in live], [q[1] for q in live], [q[2] for q in live]))
        yield pd.DataFrame(rows, columns=["win", "pos", "oid", "num"])

    return stream.groupBy("monitor").applyInPandasWithState(run, TOPM, STATE, "append", GroupStateTimeout.NoTimeout)


def time_window_counts(stream: DataFrame, size: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", delay).groupBy(window, "oid").agg(F.sum("num").alias("num"))
