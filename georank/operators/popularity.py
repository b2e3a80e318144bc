"""Contributions, popularity over count-based windows, and the continuous top-m."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .lists import columns


def contribution(rnk, n, inside=None) -> Column:
    c = F.col(n) - F.col(rnk) + 1 if isinstance(n, str) else n - F.col(rnk) + 1
    return c.cast("long") if inside is None else F.when(inside, c).otherwise(0).cast("long")


def contributions(ranked: DataFrame, n: int | DataFrame) -> DataFrame:
    """(seq, oid, num) from ranked matches; n is the number of objects, or the objects."""
    if isinstance(n, DataFrame):
        ranked, n = ranked.crossJoin(F.broadcast(n.agg(F.count("*").alias("n_objects")))), "n_objects"
    return ranked.select("seq", "oid", contribution("rnk", n).alias("num"))


def window_popularity(contribs: DataFrame, win: int | Column, w: int) -> DataFrame:
    win = F.lit(win) if isinstance(win, int) else win
    rows = contribs.filter((F.col("seq") > win - w) & (F.col("seq") <= win))
    return rows.groupBy("oid").agg(F.sum("num").alias("num")).withColumn("pop", F.col("num") / F.lit(float(w)))


def topm(pop: DataFrame, m: int, pad: DataFrame | None = None) -> DataFrame:
    """(pos, oid, num, pop); pad: all objects, of which those without popularity fill up by oid."""
    if pad is not None:
        pop = pad.select("oid").join(pop, "oid", "left").fillna({"num": 0, "pop": 0.0})
    best = pop.orderBy(F.desc("num"), "oid").limit(m)
    pos = F.row_number().over(Window.orderBy(F.desc("num"), "oid")).cast("int")
    return best.select(pos.alias("pos"), "oid", "num", "pop")


def intervals(contribs: DataFrame, w: int, last: int | Column) -> DataFrame:
    """(oid, since, until, num, touches): the numerator of each object from one change to the next; num over windows since..until-1."""
    last = F.lit(last) if isinstance(last, int) else last
    deltas = contribs.select("oid", F.explode(F.array(F.struct(F.col("seq").alias("at"), F.col("num").alias("d"), F.lit(1).cast("long").alias("t")), F.struct((F.col("seq") + w).alias("at"), (-F.col("num")).alias("d"), F.lit(-1).cast("long").alias("t")))).alias("e")).select("oid", "e.*")
    deltas = deltas.groupBy("oid", "at").agg(F.sum("d").alias("d"), F.sum("t").alias("t"))
    by = Window.partitionBy("oid").orderBy("at")
    run = by.rowsBetween(Window.unboundedPreceding, 0)
    out = deltas.select("oid", F.col("at").alias("since"), F.coalesce(F.lead("at").over(by), last + 1).alias("until"), F.sum("d").over(run).alias("num"), F.sum("t").over(run).alias("touches"))
    return out.filter("touches > 0")


def continuous_topm(contribs: DataFrame, w: int, m: int, last: DataFrame, epoch: int = 64) -> DataFrame:
    """(win, pos, oid, num, pop) for every full window. last: one row, `last`, the newest seq.

    Objects' values are intervals between changes. In each epoch of shifts, m objects never fall below the m-th largest of
    the objects' least values there, so an object that stays below it can't be in a result and isn't expanded.
    """
    end = F.broadcast(last)
    iv = _intervals_with_end(contribs, w, end)
    iv = iv.withColumn("since", F.greatest("since", F.lit(w - 1))).withColumn("until", F.least("until", F.col("last") + 1)).filter("since < until")
    cut = iv.withColumn("ep", F.explode(F.sequence(F.expr(f"since div {epoch}"), F.expr(f"(until - 1) div {epoch}"))))
    cut = cut.select("ep", "oid", "num", F.greatest("since", F.col("ep") * epoch).alias("since"), F.least("until", (F.col("ep") + 1) * epoch).alias("until"), F.least(F.col("last") + 1, (F.col("ep") + 1) * epoch).alias("stop"))
    begin = F.greatest(F.col("ep") * epoch, F.lit(w - 1))
    ends = cut.groupBy("ep", "oid").agg(F.when(F.sum(F.col("until") - F.col("since")) == F.max("stop") - F.max(begin), F.min("num")).otherwise(F.least(F.min("num"), F.lit(0))).alias("lo"), F.max("num").alias("hi"))
    nth = ends.withColumn("k", F.row_number().over(Window.partitionBy("ep").orderBy(F.desc("lo"), "oid"))).filter(F.col("k") <= m).groupBy("ep").agg(F.min("lo").alias("bar"), F.max("k").alias("k"))
    keep = ends.join(nth, "ep").filter((F.col("k") < m) | (F.col("hi") >= F.col("bar"))).select("ep", "oid")
    rows = cut.join(keep, ["ep", "oid"]).select("oid", "num", F.explode(F.sequence("since", F.col("until") - 1)).alias("win"))
    pos = F.row_number().over(Window.partitionBy("win").orderBy(F.desc("num"), "oid")).cast("int")
    return rows.withColumn("pos", pos).filter(F.col("pos") <= m).select("win", "pos", "oid", "num", (F.col("num") / F.lit(float(w))).alias("pop"))


def _intervals_with_end(contribs: DataFrame, w: int, end: DataFrame) -> DataFrame:
    iv = intervals(contribs, w, F.lit(None).cast("long"))
    return iv.crossJoin(end).withColumn("until", F.coalesce("until", F.col("last") + 1))


def result_changes(top: DataFrame, chunk: int = 8192) -> DataFrame:
    """(win) at which the ordered result differs from the one before; the first window counts.

    top is made and moved once: windows are compared in chunks, which get the last window of the chunk before them too.
    """
    ends = F.when(F.expr(f"win % {chunk} = {chunk - 1}"), F.expr(f"array(win div {chunk}, win div {chunk} + 1)")).otherwise(F.expr(f"array(win div {chunk})"))
    rows = top.select(F.explode(ends).alias("c"), "win", "pos", "oid")

    def changes(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        win, pos, oid = columns(batches, ("win", "pos", "oid"))
        by = np.lexsort((oid, pos, win))
        oid, (wins, begin, size) = oid[by], np.unique(win[by], return_index=True, return_counts=True)
        # Windows as long as the window before, one less; of them those of which some place is as it was no longer.
        k = 1 + np.flatnonzero((np.diff(wins) == 1) & (np.diff(size) == 0))
        which = np.repeat(k, size[k])
        nth = np.arange(len(which)) - np.repeat(np.cumsum(size[k]) - size[k], size[k])
        same = np.zeros(len(wins), bool)
        same[k] = True
        same[which[oid[begin[which] + nth] != oid[begin[which - 1] + nth]]] = False
        yield pa.RecordBatch.from_arrays([pa.array(wins[~same & (wins >= key[0].as_py() * chunk)])], ["win"])

    return rows.groupBy("c").applyInArrow(changes, "win long")


def est_rank2(lo_rank, slack: int, n=None) -> Column:
    """Twice the rank estimate (1 + slack/2) * lo_rank; with n, clamped to twice n."""
    e = (2 + slack) * F.col(lo_rank)
    return (e if n is None else F.least(e, 2 * F.col(n))).cast("long")
