"""Choices made before Spark plans: tiers, canonical construction, deferral of filters, literal prefilters, shared prefixes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternlm.functions import automata as fa
from patternlm.functions.regex import parse, required_literals
from patternlm.plans.query import PatternQuery, Preprocessor

SMALL_EDGES = 100_000
GROWTH = 2.0


def choose_tier(n_edges: int, n_counts: int, n_queries: int, most_counts: int = 5_000_000) -> str:
    """driver (one small query), in_task (many small ones, packed model), or frontier (joins)."""
    if n_edges > SMALL_EDGES or n_counts > most_counts:
        return "frontier"
    return "driver" if n_queries == 1 else "in_task"


def defer_filters(query: PatternQuery) -> PatternQuery:
    """Exclusions that would more than double the automaton become run-time filters."""
    base = query.but(preprocessors=tuple(p for p in query.preprocessors if p.kind != "exclude")).automaton()
    out: list[Preprocessor] = []
    for p in query.preprocessors:
        if p.kind == "exclude" and not p.deferred:
            grown = fa.difference(base, fa.words_dfa(p.args["words"]))
            p = Preprocessor("exclude", p.args, deferred=grown.size[0] > GROWTH * max(base.size[0], 1))
        out.append(p)
    return query.but(preprocessors=tuple(out))


def pattern_filter(col: str, pattern: str) -> Column:
    """pattern as a predicate, behind a certain literal where it has one."""
    literal = required_literals(parse(pattern))
    exact = F.col(col).rlike(pattern)
    return F.contains(F.col(col), F.lit(literal)) & exact if literal else exact


def share_prefixes(queries: DataFrame, prefix: str = "prompt", n_chars: int = 12) -> DataFrame:
    """Queries grouped so that those with the same beginning run in the same task, where the model's cache serves them together."""
    return queries.withColumn("bucket", F.xxhash64(F.substring(prefix, 1, n_chars))).repartition("bucket").sortWithinPartitions("bucket", prefix).drop("bucket")


def grid(axes: dict[str, Sequence], cell) -> DataFrame:
    """One row of results for each combination of settings."""
    rows, keys = [{}], list(axes)
    for k in keys:
        rows = [r | {k: v} for r in rows for v in axes[k]]
    out = None
    for r in rows:
        got = cell(**r)
        for k in reversed(keys):
            got = got.select(F.lit(r[k]).alias(k), "*")
        out = got if out is None else out.unionByName(got)
    return out


def explain(query: PatternQuery) -> str:
    """The query's own plan: sizes of its automata and the choices made."""
    dfa = query.automaton()
    finite = fa.is_finite(dfa)
    lines = [f"pattern: prefix={query.prefix!r} body={query.body!r}", f"automaton: {dfa.size[0]} states, {dfa.size[1]} edges, {'finite' if finite else 'infinite'}"]
    if finite:
        lines.append(f"strings: {fa.walks(dfa, 256)[-1][0]}")
    lines.append(f"encoding: {query.encoding}, rules: {query.rules}, traversal: {query.traversal}")
    lines += [f"preprocessor: {p.kind}{' (run time)' if p.deferred else ''}" for p in query.preprocessors]
    return "\n".join(lines)
