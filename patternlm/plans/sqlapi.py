"""SQL surface: table functions for patterns and tokens."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from patternlm.functions import automata as fa
from patternlm.functions.tokenizer import TOY_MERGES, Tokenizer
from patternlm.operators.model import NextTokenModel
from patternlm.operators.traverse import run_query
from patternlm.plans.query import PatternQuery, Rules


def register(spark: SparkSession, model: NextTokenModel | None = None, tokenizer: Tokenizer | None = None) -> None:
    """regex_edges(pattern), tokenize(text), and with a model pattern_match(body, prefix, top_k, n)."""
    tok = tokenizer or Tokenizer(TOY_MERGES, "abcdefghijklmnopqrstuvwxyz ")

    @udtf(returnType="src int, sym string, dst int, is_final boolean")
    class RegexEdges:
        def eval(self, pattern: str):
            dfa = fa.compile_regex(pattern)
            for s, c, t, _ in dfa.rows():
                yield s, c, t, t in dfa.finals

    @udtf(returnType="pos int, token_id int, token string")
    class Tokenize:
        def eval(self, text: str):
            for i, t in enumerate(tok.encode(text)):
                yield i, t, tok.text.get(t, "")

    spark.udtf.register("regex_edges", RegexEdges)
    spark.udtf.register("tokenize", Tokenize)
    if model is None:
        return

    @udtf(returnType="match_rank long, text string, logp double")
    class PatternMatch:
        def eval(self, body: str, prefix: str, top_k: int, n: int):
            query = PatternQuery(body, prefix, encoding="all", rules=Rules(top_k=top_k))
            for row in run_query(query, model, tok, n):
                yield row[1], row[3], row[5]

    spark.udtf.register("pattern_match", PatternMatch)
