"""Quality rules: a threshold table compiled into one projection of built-in functions.

Statistics of a text (null: no words, no lines): words are `[^\\x20\\x09-\\x0D]+`, lines are split at \\n. A rule names a statistic, a
comparison that rejects, and a threshold; a document is kept if its base test passes and no rule rejects it. Empty texts
have no words and so fail the base test. Stop words are those of STOP_WORDS, as written there (lower case): texts of other languages, and texts
in capitals throughout, have none and are rejected by `no_stop_words`. Extra columns are kept by keep_good, whatever their names. Repeated 8-word windows are found by 64-bit hashes of the windows of one text.
"""

from __future__ import annotations

from collections.abc import Sequence
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from patternlm.llm.common import column, let, whole_row, words

WINDOW = 8

# Frequent function words by language.
STOP_WORDS = {
    "en": "the of and to a in is was for that with as by it on be this are at from or an",
    "fr": "le la les de des et un une du en est que qui pour dans par sur au il elle",
    "de": "der die das und von zu den ist mit im des ein eine nicht auf für dem sie es",
    "es": "el la los las de que y en un una por con para del se su es lo al",
}
SYMBOLS = r"[#*$%&|<>]"


class Rule(NamedTuple):
    name: str
    stat: str
    rejects: str  # "<" or ">"
    threshold: float


RULES = (
    Rule("few_words", "n_words", "<", 20),
    Rule("short_words", "mean_word_chars", "<", 2),
    Rule("long_words", "mean_word_chars", ">", 14),
    Rule("symbols", "symbols_per_word", ">", 0.1),
    Rule("shouting", "shouted_share", ">", 0.3),
    Rule("no_stop_words", "stop_word_share", "<", 0.02),
    Rule("repeated_lines", "dup_line_share", ">", 0.5),
    Rule("bullet_lines", "bullet_line_share", ">", 0.9),
    Rule("ellipsis_lines", "ellipsis_line_share", ">", 0.3),
)


def _paired(hashes: Column, step: int) -> Column:
    """Element i hashed with element i+step."""

    def body(a: Column) -> Column:
        n = F.greatest(F.size(a) - step, F.lit(0))
        return F.zip_with(F.slice(a, 1, n), F.slice(a, step + 1, n), lambda x, y: F.xxhash64(x, y))

    return let(hashes, body)


def window_hashes(w: Column) -> Column:
    """A hash for each window of 8 words, in order, by three doublings."""
    return _paired(_paired(_paired(F.transform(w, lambda x: F.xxhash64(x)), 1), 2), 4)


def _covered(windows: Column) -> Column:
    """Words that lie in a window found at least twice."""

    def body(s: Column) -> Column:
        same = lambda e, i: F.coalesce(F.get(s, i - 1)["h"] == e["h"], F.lit(False)) | F.coalesce(F.get(s, i + 1)["h"] == e["h"], F.lit(False))
        return F.sort_array(F.transform(F.filter(s, same), lambda e: e["i"]))

    def total(p: Column) -> Column:
        n = F.size(p) - 1
        gaps = F.zip_with(F.slice(p, 2, n), F.slice(p, 1, n), lambda b, a: F.least(b - a, F.lit(WINDOW)))
        return F.aggregate(gaps, F.lit(WINDOW).cast("int"), lambda acc, g: acc + g)

    ranked = F.sort_array(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    return let(let(ranked, body), total)


def repeated_words(w: Column) -> Column:
    return let(window_hashes(w), lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(_covered(h))).cast("long")


def statistics(text: Column) -> Column:
    """One struct of all statistics of a text."""
    text = F.coalesce(text, F.lit(""))
    stops = F.array(*(F.lit(x) for x in dict.fromkeys(" ".join(STOP_WORDS.values()).split())))

    def of_lines(lines: Column) -> list[Column]:
        n = F.greatest(F.size(lines), F.lit(1))
        return [
            (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
            F.size(lines).cast("long").alias("n_lines"),
            (F.size(F.filter(lines, lambda x: x.rlike(r"^[\x20\t]*[-*•]"))) / n).alias("bullet_line_share"),
            (F.size(F.filter(lines, lambda x: x.rlike(r"(\.\.\.|…)[\x20\t\r]*$"))) / n).alias("ellipsis_line_share"),
        ]

    def of_words(w: Column) -> list[Column]:
        n = F.greatest(F.size(w), F.lit(1))
        return [
            F.size(w).cast("long").alias("n_words"),
            F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
            repeated_words(w).alias("n_repeat_words"),
            (F.size(F.filter(w, lambda x: F.array_contains(stops, x))) / n).alias("stop_word_share"),
            (F.size(F.filter(w, lambda x: F.endswith(x, F.lit("!!")))) / n).alias("shouted_share"),
        ]

    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    symbols = (F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).cast("long")
    return F.struct(let(words(text), lambda w: F.struct(*of_words(w))).alias("w"), let(lines, lambda x: F.struct(*of_lines(x))).alias("l"), symbols.alias("n_symbols"))


def measured(docs: DataFrame, text_col: str = "text", into: str = "__q") -> DataFrame:
    """docs with one struct column of named statistics."""
    # a generated column is computed once: a later filter on it can't be pushed below and repeat the expression for each use
    raw = docs.select("*", F.explode_outer(F.array(statistics(column(text_col)))).alias(into))
    w, x = F.col(into)["w"], F.col(into)["l"]
    n = F.greatest(w["n_words"], F.lit(1))
    flat = {k: w[k] for k in ("n_words", "word_chars", "n_repeat_words", "stop_word_share", "shouted_share")} | {k: x[k] for k in ("n_dup_lines", "n_lines", "bullet_line_share", "ellipsis_line_share")}
    flat |= {"n_symbols": F.col(into)["n_symbols"], "mean_word_chars": w["word_chars"] / n, "symbols_per_word": F.col(into)["n_symbols"] / n, "dup_line_share": x["n_dup_lines"] / F.greatest(x["n_lines"], F.lit(1))}
    return raw.withColumn(into, F.struct(*(v.alias(k) for k, v in flat.items())))


def compiled(rules: Sequence[Rule], stats: Column) -> Column:
    """The names of the rules that reject, as one array expression."""
    broken = [F.when((stats[r.stat] < r.threshold) if r.rejects == "<" else (stats[r.stat] > r.threshold), F.lit(r.name)) for r in rules]
    return F.array_compact(F.array(*broken)) if broken else F.array().cast("array<string>")


def base_failed(stats: Column) -> Column:
    return (stats["n_words"] < 20) | (100 * stats["n_repeat_words"] > 30 * stats["n_words"])


def judge(docs: DataFrame, rules: Sequence[Rule] = RULES, text_col: str = "text") -> DataFrame:
    """docs with __q (statistics), __broken (rules that reject), __base (base test failed), __kept."""
    out = measured(docs, text_col)
    q = F.col("__q")
    out = out.withColumn("__broken", compiled(rules, q)).withColumn("__base", base_failed(q))
    return out.withColumn("__kept", ~F.col("__base") & (F.size("__broken") == 0))


def quality_rules(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rules: Sequence[Rule] = RULES) -> DataFrame:
    """Every row of docs: its statistics, base_failed and kept."""
    q = F.col("__q")
    out = judge(docs.select(column(id_col).alias("doc_id"), column(text_col).alias("text")), rules)
    return out.select("doc_id", *(q[c].alias(c) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")), F.col("__base").alias("base_failed"), F.col("__kept").alias("kept"), F.array_join("__broken", ",").alias("broken_rules"))


def keep_good(docs: DataFrame, text_col: str = "text", rules: Sequence[Rule] = RULES) -> DataFrame:
    """The rows of docs that no rule rejects, with their columns."""
    rows = docs.select(whole_row(docs).alias("row"), column(text_col).alias("text"))
    return judge(rows, rules).where("__kept").select("row.*")
