"""Monitors as stateful operators over a prepared stream: one ordered pass per monitor, everything else set-oriented before it."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.monitor import Monitor, reached

COLUMNS = ["monitor", "win", "pos", "oid", "num", "outcome", "opq_validation", "opq_total", "t_block", "t_object", "t_valid"]
REPLAY = "monitor string, win long, pos int, oid long, num long, outcome string, opq_validation long, opq_total long, t_block double, t_object double, t_valid double"


def prepare(contribs: DataFrame, queries: DataFrame, order: str = "lo_rank") -> DataFrame:
    """(seq, oids, nums): each query's reach in rank-list order; queries that reach nothing have empty lists."""
    packed = contribs.groupBy("seq").agg(F.array_sort(F.collect_list(F.struct(F.col(order).alias("o"), "oid", "num"))).alias("e"))
    packed = packed.select("seq", F.transform("e", lambda s: s["oid"]).alias("oids"), F.transform("e", lambda s: s["num"]).alias("nums"))
    empty = F.array().cast("array<bigint>")
    return queries.select("seq").join(packed, "seq", "left").select("seq", F.coalesce("oids", empty).alias("oids"), F.coalesce("nums", empty).alias("nums"))


def replay(prepared: DataFrame, n: int, w: int, m: int, cmax: int, modes: dict[str, dict], block: int = 128) -> DataFrame:
    """Results and costs per window of each named monitor; a mode may set its own w, m and block.

    Monitors run beside one another, shifts of one are sequential: its queries stream by in order of seq, and a task holds one window's
    queries and one Arrow batch, whatever the stream's length.
    """
    names = F.array(*[F.lit(k) for k in modes])

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        name, own, live, mon = None, {}, [], None
        for pdf in batches:
            rows = []
            for key, seq, oids, nums in zip(pdf.monitor, pdf.seq, pdf.oids, pdf.nums):
                if key != name:
                    name, own, live = key, {"w": w, "m": m, "block": block} | modes[key], []
                    mon = Monitor(n, cmax=cmax, **own)
                q = reached(list(map(int, oids)), list(map(int, nums)), own["block"])
                if live is not None:
                    live.append(q)
                    if len(live) < own["w"]:
                        continue
                    res, cost, live = mon.start(live), {"outcome": "first"}, None
                else:
                    res, cost = mon.step(q)
                rows += [(key, seq, pos, oid, num, *[cost.get(c, 0) for c in COLUMNS[5:]]) for pos, (oid, num) in enumerate(res, 1)]
            yield pd.DataFrame(rows, columns=COLUMNS)

    each = prepared.withColumn("monitor", F.explode(names)).select("monitor", "seq", "oids", "nums")
    return each.repartition(len(modes), "monitor").sortWithinPartitions("monitor", "seq").mapInPandas(run, REPLAY)
