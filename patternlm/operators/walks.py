"""Walk counts, edge weights, unranking and enumeration of automata as relations.

Edges: (query_id, src, sym, dst); finals: (query_id, state). Counts are DECIMAL(38,0) (ANSI mode raises on overflow).
Automata are plan-sized; each round is one join on (query_id, state) and one aggregate.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternlm.session import cut

BIG = "decimal(38,0)"


def _union(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def walks_by_length(edges: DataFrame, finals: DataFrame, max_len: int) -> DataFrame:
    """(query_id, state, len, n): strings of exactly len symbols from state to an end."""
    level = finals.select("query_id", "state", F.lit(0).alias("len"), F.lit(1).cast(BIG).alias("n"))
    levels = [level]
    for k in range(1, max_len + 1):
        step = edges.join(level.select("query_id", F.col("state").alias("dst"), "n"), ["query_id", "dst"])
        level = step.groupBy("query_id", F.col("src").alias("state")).agg(F.sum("n").cast(BIG).alias("n")).select("query_id", "state", F.lit(k).alias("len"), "n")
        level = cut(level, "walks")
        levels.append(level)
    return _union(levels)


def walks_total(edges: DataFrame, finals: DataFrame, max_len: int) -> DataFrame:
    """(query_id, state, n): strings of at most max_len symbols."""
    return walks_by_length(edges, finals, max_len).groupBy("query_id", "state").agg(F.sum("n").cast(BIG).alias("n"))


def edge_weights(edges: DataFrame, finals: DataFrame, max_len: int) -> DataFrame:
    """Each edge's share of the strings that leave its source, with cumulative bounds, and the chance to stop there first."""
    w = walks_total(edges, finals, max_len)
    met = edges.join(w.select("query_id", F.col("state").alias("dst"), "n"), ["query_id", "dst"])
    met = met.join(finals.select("query_id", F.col("state").alias("src"), F.lit(1).alias("ends")), ["query_id", "src"], "left")
    by, order = Window.partitionBy("query_id", "src"), Window.partitionBy("query_id", "src").orderBy("sym")
    leaving = F.sum("n").over(by)
    upto = F.sum("n").over(order.rowsBetween(Window.unboundedPreceding, 0))
    met = met.withColumn("p", F.round((F.col("n") / leaving).cast("double"), 6)).withColumn("cum_hi", F.round((upto / leaving).cast("double"), 6))
    stop = F.coalesce("ends", F.lit(0)) / (leaving + F.coalesce("ends", F.lit(0)))
    return met.select("query_id", "src", "sym", "dst", F.col("n").cast("long").alias("n"), "p", F.round(F.col("cum_hi") - F.col("p"), 6).alias("cum_lo"), "cum_hi", F.round(stop.cast("double"), 6).alias("stop_p"))


def edge_uniform(edges: DataFrame) -> DataFrame:
    """Naive weights: every edge of a state alike."""
    return edges.withColumn("p", F.round(1 / F.count("*").over(Window.partitionBy("query_id", "src")), 6))


def enumerate_strings(edges: DataFrame, finals: DataFrame, max_len: int) -> DataFrame:
    """(query_id, text, len): all strings of at most max_len symbols (for languages that are small)."""
    level = finals.select("query_id").distinct().select("query_id", F.lit(0).alias("state"), F.lit("").alias("text"), F.lit(0).alias("len"))
    levels = [level]
    for k in range(1, max_len + 1):
        step = level.join(edges.select("query_id", F.col("src").alias("state"), "sym", "dst"), ["query_id", "state"])
        level = step.select("query_id", F.col("dst").alias("state"), F.concat("text", "sym").alias("text"), F.lit(k).alias("len"))
        levels.append(level)
    return _union(levels).join(finals.select("query_id", "state"), ["query_id", "state"], "left_semi").select("query_id", "text", "len")


def unrank(indices: DataFrame, edges: DataFrame, finals: DataFrame, max_len: int) -> DataFrame:
    """indices (query_id, idx) -> (query_id, idx, text): the idx-th string, by joins of the remaining index with cumulative counts.

    A string stops at a final state with remaining index 0; else one is subtracted there and the edge whose interval of counts (edges by symbol,
    strings of the length left) holds the index is taken.
    """
    by_len = walks_by_length(edges, finals, max_len)
    upto = Window.partitionBy("query_id", "state").orderBy("len").rowsBetween(Window.unboundedPreceding, 0)
    spread = by_len.select("query_id", "state").distinct().select("query_id", "state", F.explode(F.sequence(F.lit(0), F.lit(max_len))).alias("len"))
    within = spread.join(by_len, ["query_id", "state", "len"], "left").withColumn("w", F.sum(F.coalesce("n", F.lit(0).cast(BIG))).over(upto))
    within = cut(within, "walks")
    ends = finals.select("query_id", "state", F.lit(1).alias("ends"))
    rows = indices.select("query_id", "idx", F.lit(0).alias("state"), F.col("idx").cast(BIG).alias("rest"), F.lit("").alias("text"), F.lit(False).alias("done"))
    for left in range(max_len, -1, -1):
        at = rows.where("NOT done").join(ends, ["query_id", "state"], "left")
        stop = at.where("ends = 1 AND rest = 0").select("query_id", "idx", "state", "rest", "text", F.lit(True).alias("done"))
        going = at.where("NOT coalesce(ends = 1 AND rest = 0, false)").withColumn("rest", F.col("rest") - F.coalesce("ends", F.lit(0)))
        finished = [rows.where("done"), stop]
        if left == 0:
            rows = _union(finished)
            break
        counts = within.where(F.col("len") == left - 1).select("query_id", F.col("state").alias("dst"), "w")
        order = Window.partitionBy("query_id", "src").orderBy("sym").rowsBetween(Window.unboundedPreceding, 0)
        arcs = edges.join(counts, ["query_id", "dst"]).withColumn("hi", F.sum("w").over(order)).withColumn("lo", F.col("hi") - F.col("w"))
        step = going.join(arcs.withColumnRenamed("src", "state"), ["query_id", "state"]).where("rest >= lo AND rest < hi")
        step = step.select("query_id", "idx", F.col("dst").alias("state"), (F.col("rest") - F.col("lo")).cast(BIG).alias("rest"), F.concat("text", "sym").alias("text"), F.lit(False).alias("done"))
        rows = cut(_union([*finished, step]), "unrank")
    return rows.where("done").select("query_id", "idx", "text")
