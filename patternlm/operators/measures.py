"""Measures over matches and samples; each is one pass and at most one shuffle by its key unless it says more."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternlm.session import cut


RUN = 1 << 16


def valid_unique(attempts: DataFrame, truth: DataFrame, on: str, by: Sequence[str] = ()) -> DataFrame:
    """Attempts, valid ones, distinct valid texts, and completion (distinct valid / attempts)."""
    known = truth.select(F.col(on).alias("__t")).distinct()
    met = attempts.join(known, F.col(on) == F.col("__t"), "left").withColumn("ok", F.col("__t").isNotNull())
    out = met.groupBy(*by).agg(F.count("*").alias("attempts"), F.count_if("ok").alias("valid"), F.countDistinct(F.when(F.col("ok"), F.col(on))).alias("valid_unique"))
    return out.withColumn("completion", F.round(F.col("valid_unique") / F.col("attempts"), 6))


def duplicate_rate(rows: DataFrame, on: str, by: Sequence[str] = ()) -> DataFrame:
    out = rows.groupBy(*by).agg(F.count(on).alias("n"), F.countDistinct(on).alias("uniq"))
    return out.withColumn("dup_rate", F.round(1 - F.col("uniq") / F.col("n"), 6))


def discovery_curve(attempts: DataFrame, order: str, on: str) -> DataFrame:
    """Distinct texts found up to each attempt."""
    first = (F.row_number().over(Window.partitionBy(on).orderBy(order)) == 1).cast("long")
    marked = attempts.select(F.col(order).cast("long").alias(order), first.alias("fresh")).withColumn("run", F.expr(f"{order} div {RUN}"))
    runs = marked.groupBy("run").agg(F.sum("fresh").alias("held"))  # attempts are summed by runs first, so that no task orders all of them
    base = runs.select("run", F.coalesce(F.sum("held").over(Window.orderBy("run").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    inside = F.sum("fresh").over(Window.partitionBy("run").orderBy(order).rowsBetween(Window.unboundedPreceding, 0))
    return marked.withColumn("inside", inside).join(base, "run").select(order, (F.col("inside") + F.col("base")).alias("found"))


def cond_dist(samples: DataFrame, x: str, y: str, weight: Column | None = None) -> DataFrame:
    """P(y given x), from counts or weights."""
    w = F.lit(1) if weight is None else weight
    n = samples.groupBy(x, y).agg(F.sum(w).alias("n"))
    return n.withColumn("p", F.round(F.col("n") / F.sum("n").over(Window.partitionBy(x)), 6))


def log_upper_gamma(a: float, x: float) -> float:
    """ln of the regularised upper incomplete gamma function, by series below a+1 and by continued fraction above."""
    if x <= 0:
        return 0.0
    if x < a + 1:
        term = total = 1 / a
        n = a
        while term > total * 1e-17:
            n += 1
            term *= x / n
            total += term
        lower = math.exp(-x + a * math.log(x) - math.lgamma(a)) * total
        return math.log1p(-lower) if lower < 1 else -math.inf
    tiny = 1e-300
    b = x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = an * d + b
        d = 1 / (d if abs(d) > tiny else tiny)
        c = b + an / c
        c = c if abs(c) > tiny else tiny
        h *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return -x + a * math.log(x) - math.lgamma(a) + math.log(h)


def chi2_sf_log10(stat: float, dof: int) -> float:
    return log_upper_gamma(dof / 2, stat / 2) / math.log(10) if dof > 0 else 0.0


def chi2_parts(table: DataFrame, x: str, y: str, n: str = "n", by: Sequence[str] = ()) -> DataFrame:
    """Statistic and degrees of freedom of x against y, for each group of by. Empty rows and columns have no part."""
    over = lambda *c: Window.partitionBy(*by, *c)
    t = table.where(F.col(n) > 0)
    xs = t.select(*by, x).distinct()
    ys = t.select(*by, y).distinct()
    full = xs.join(ys, list(by)) if by else xs.join(F.broadcast(ys), F.lit(True))  # the table's own cells
    full = full.join(t.select(*by, x, y, n), [*by, x, y], "left").fillna(0, [n])
    row, col, total = F.sum(n).over(over(x)), F.sum(n).over(over(y)), F.sum(n).over(over())
    cells = full.withColumn("expected", row * col / total)
    out = cells.groupBy(*by).agg(F.round(F.sum((F.col(n) - F.col("expected")) ** 2 / F.col("expected")), 6).alias("stat"), ((F.countDistinct(x) - 1) * (F.countDistinct(y) - 1)).alias("dof"), F.sum(n).alias("total"))
    return out


def chi2(table: DataFrame, x: str, y: str, n: str = "n", by: Sequence[str] = ()) -> DataFrame:
    """chi2_parts with log10 of the p-value (the tail may be far below the smallest double)."""
    tail = F.udf(lambda s, k: float(chi2_sf_log10(s or 0.0, k or 0)), "double")  # a row per test; an empty table has no evidence
    return chi2_parts(table, x, y, n, by).withColumn("log10_p", tail("stat", "dof"))


def per_outcome(table: DataFrame, x: str, y: str, n: str = "n") -> DataFrame:
    """2 x 2 tests: each outcome against all others."""
    outcomes = table.select(F.col(y).alias("outcome")).distinct()
    tagged = table.join(F.broadcast(outcomes), F.lit(True)).withColumn("is_it", F.col(y) == F.col("outcome"))
    return chi2(tagged.groupBy("outcome", x, "is_it").agg(F.sum(n).alias(n)), x, "is_it", n, ["outcome"])


def log_sum_exp(rows: DataFrame, value: str, by: Sequence[str] = (), step: int = 300) -> DataFrame:
    """(by, log_sum): ln of the sum of e**value, in two combined aggregates. Values are summed within spans of `step`, where doubles suffice, then over the few spans.

    Null values are left out; -inf adds nothing, and a group with nothing else has -inf.
    """
    span = F.when(F.col(value) > F.lit(float("-inf")), F.floor(F.col(value) / step))
    parts = rows.where(F.col(value).isNotNull()).withColumn("__span", span).groupBy(*by, "__span").agg(F.sum(F.exp(F.col(value) - F.col("__span") * step)).alias("__s"))
    logs = F.collect_list(F.col("__span") * step + F.log("__s"))
    top = F.array_max("__l")
    total = F.aggregate(F.transform("__l", lambda x: F.exp(x - top)), F.lit(0.0), lambda a, x: a + x)
    return parts.groupBy(*by).agg(logs.alias("__l")).select(*by, F.when(F.size("__l") > 0, top + F.log(total)).otherwise(float("-inf")).alias("log_sum"))


def encoding_ratio(model, a: Sequence[int], b: Sequence[int], ctx: tuple[int, ...]) -> float:
    """How much likelier encoding a is than b after ctx."""
    return math.exp(model.score(a, ctx) - model.score(b, ctx))


def first_difference(original: str, edited: str) -> Column:
    """The first position (from 1) at which two text columns differ; one past the shorter where that is a beginning of the other."""
    n = F.least(F.length(original), F.length(edited))
    differs = F.filter(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.substr(F.col(original), i, F.lit(1)) != F.substr(F.col(edited), i, F.lit(1)))
    return F.coalesce(F.get(differs, F.lit(0)), n + 1)


def edit_positions(samples: DataFrame, original: str, edited: str) -> DataFrame:
    """Samples by the first position at which the edited text differs."""
    changed = samples.where(F.col(original) != F.col(edited)).withColumn("edit_pos", first_difference(original, edited))
    total = F.sum("n").over(Window.partitionBy())
    return changed.groupBy("edit_pos").agg(F.count("*").alias("n")).withColumn("share", F.round(F.col("n") / total, 6))


def neighbour_positions(words: DataFrame, col: str, letters: int) -> DataFrame:
    """edit_positions of all texts one edit from each word (over an alphabet of so many letters, the word's own among them), counted and not listed.

    At each place a text first differs by another letter in its stead, by another letter before it, and by a deletion at the end of a run of equal letters (deleting
    any of a run gives one text). Past the end any letter can be added. No two of these texts are equal.
    """
    at = lambda i: F.substr(F.col(col), i, F.lit(1))
    size = F.length(col)
    own = F.transform(F.sequence(F.lit(1), size + 1), lambda i: F.struct(i.cast("int").alias("edit_pos"), F.when(i > size, letters).otherwise(2 * (letters - 1) + (at(i) != at(i + 1)).cast("int")).cast("long").alias("n")))
    by = words.select(F.explode(own).alias("p")).groupBy("p.edit_pos").agg(F.sum("p.n").alias("n"))
    return by.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6))


def success_rate(matches: DataFrame, queries: DataFrame, by: Sequence[str] = ()) -> DataFrame:
    """Queries with a match over queries; queries without a match count."""
    hit = matches.select("query_id", *by).distinct().withColumn("hit", F.lit(1))
    met = queries.join(hit, ["query_id", *by], "left")
    return met.groupBy(*by).agg(F.count("*").alias("queries"), F.coalesce(F.sum("hit"), F.lit(0)).alias("successes"), F.round(F.coalesce(F.sum("hit"), F.lit(0)) / F.count("*"), 6).alias("success"))


def volume(matches: DataFrame, cap: int = 1000) -> DataFrame:
    """Matches by query, counted up to the cap, and the running mean over queries."""
    by = matches.groupBy("query_id").agg(F.least(F.count("*"), F.lit(cap)).alias("volume"))
    return by.withColumn("mean_volume", F.round(F.avg("volume").over(Window.partitionBy()), 6))


def edit_encoding_cube(matches: DataFrame) -> DataFrame:
    """Matches and share by (edited, canonical), with subtotals. The matches are made once: their counts are a table of four rows at most."""
    flags = matches.select((F.col("n_edits") > 0).alias("edited"), F.col("is_canonical").alias("canonical"))
    counts = cut(flags.groupBy("edited", "canonical").agg(F.count("*").alias("n")), "edit-encoding")
    total = counts.agg(F.sum("n").alias("total"))
    cube = counts.cube("edited", "canonical").agg(F.sum("n").alias("n"))
    return cube.join(F.broadcast(total), F.lit(True)).select("edited", "canonical", "n", F.round(F.col("n") / F.col("total"), 6).alias("share"))


def edit_chars(pairs: DataFrame, original: str, edited: str, k: int = 10) -> DataFrame:
    """The characters that edits most often add and remove (multiset differences of each pair of texts)."""
    chars = lambda c: F.filter(F.split(c, ""), lambda x: x != "")
    less = lambda a, b: F.filter(F.array_distinct(a), lambda x: F.size(F.filter(a, lambda y: y == x)) > F.size(F.filter(b, lambda y: y == x)))
    o, e = chars(F.col(original)), chars(F.col(edited))
    rows = pairs.select(F.explode(F.concat(F.transform(less(e, o), lambda c: F.struct(F.lit("added").alias("op"), c.alias("c"))), F.transform(less(o, e), lambda c: F.struct(F.lit("removed").alias("op"), c.alias("c"))))).alias("s")).select("s.*")
    n = rows.groupBy("op", "c").agg(F.count("*").alias("n"))
    return n.withColumn("rnk", F.row_number().over(Window.partitionBy("op").orderBy(F.desc("n"), "c"))).where(F.col("rnk") <= k)


def amplification(all_features: float, baseline: float) -> float:
    return all_features / baseline if baseline else math.inf


def accuracy(predicted: DataFrame, pred: str = "pred", answer: str = "answer", by: Sequence[str] = ()) -> DataFrame:
    return predicted.groupBy(*by).agg(F.count("*").alias("items"), F.count_if(F.col(pred) == F.col(answer)).alias("correct"), F.round(F.avg((F.coalesce(F.col(pred) == F.col(answer), F.lit(False))).cast("double")), 6).alias("accuracy"))


def concentration(predicted: DataFrame, pred: str = "pred", k: int = 5, by: Sequence[str] = ()) -> DataFrame:
    """Share of the k commonest predictions."""
    n = predicted.where(F.col(pred).isNotNull()).groupBy(*by, pred).agg(F.count("*").alias("n"))
    ranked = n.withColumn("rnk", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("n"), pred))).withColumn("total", F.sum("n").over(Window.partitionBy(*by)))
    return ranked.where(F.col("rnk") <= k).groupBy(*by).agg(F.round(F.sum("n") / F.first("total"), 6).alias("share"))


def truth_rank(matches: DataFrame, truth: DataFrame, on: Sequence[str]) -> DataFrame:
    """The rank of the true answer among the matches of its query (null if it is not there)."""
    return truth.join(matches.select(*on, "match_rank"), list(on), "left")


def noncanonical_rate(samples: DataFrame) -> DataFrame:
    return samples.agg(F.count("*").alias("n"), F.round(F.avg((~F.col("is_canonical")).cast("double")), 6).alias("rate"))


def graph_stats(edges: DataFrame, states: DataFrame) -> DataFrame:
    e = edges.groupBy("query_id").agg(F.count("*").alias("edges"))
    return states.groupBy("query_id").agg(F.count("*").alias("states"), F.count_if("is_final").alias("finals")).join(e, "query_id", "left").fillna(0, ["edges"])


def edit_false_positives(matches: DataFrame, words: Sequence[str]) -> DataFrame:
    """Edited matches that no longer hold an intact listed word, over edited matches."""
    edited = matches.where("n_edits > 0").withColumn("kept", F.col("text").rlike("|".join(words)))
    return edited.agg(F.count("*").alias("edited"), F.count_if(~F.col("kept")).alias("lost"), F.round(F.avg((~F.col("kept")).cast("double")), 6).alias("false_positives"))


def failure_classes(graded: DataFrame) -> DataFrame:
    """Attempts by outcome: valid, duplicate, invented (well formed, not in truth), cut short, malformed. graded has attempt, text, ended, in_pattern, in_truth."""
    again = F.row_number().over(Window.partitionBy("text").orderBy("attempt")) > 1
    kind = F.when(F.col("in_truth") & again, "duplicate").when(F.col("in_truth"), "valid").when(F.col("in_pattern"), "invented").when(~F.col("ended"), "cut short").otherwise("malformed")
    return graded.withColumn("outcome", kind).groupBy("outcome").agg(F.count("*").alias("n"))


def rule_effect(free: DataFrame, ruled: DataFrame) -> DataFrame:
    """Results with and without decision rules."""
    return free.agg(F.count("*").alias("without_rules")).join(F.broadcast(ruled.agg(F.count("*").alias("with_rules"))), F.lit(True))


def run_metrics(query, model, tokenizer, limit: int | None = None, **options) -> dict[str, float]:
    """Cost of one query on the driver: results, seconds, seconds to the first result, pops, model look-ups, and the share of time the model was busy."""
    import time

    from patternlm.operators.traverse import TRAVERSALS

    busy, plain = [0.0], {name: getattr(model, name) for name in ("ruled", "logp", "prefetch")}

    def timed(f):
        def run(*a):
            began = time.perf_counter()
            try:
                return f(*a)
            finally:
                busy[0] += time.perf_counter() - began

        return run

    lookups, began, first, n, pops = model.lookups, time.perf_counter(), None, 0, 0
    for name, f in plain.items():
        setattr(model, name, timed(f))
    try:
        for m in TRAVERSALS[query.traversal](query, model, tokenizer, limit, **options):
            n, pops = n + 1, m.pops
            first = time.perf_counter() - began if first is None else first
    finally:
        for name in plain:
            delattr(model, name)
    sec = time.perf_counter() - began
    return {"results": n, "sec": sec, "first_result_sec": first, "pops": pops, "lookups": model.lookups - lookups, "busy_share": min(1.0, busy[0] / sec) if sec else 0.0}
