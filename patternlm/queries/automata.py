"""Automata, tokenizers and preprocessors on literal inputs and on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from patternlm.functions import automata as fa
from patternlm.functions.tokenizer import TOY_MERGES, Tokenizer
from patternlm.operators import graph, walks
from patternlm.queries import query
from patternlm.session import cut
from patternlm.sources.io import english_words, table

PATTERNS = {1: "(a|b|bb|bbb)", 2: "(ab?|c)(d|e)?", 3: "a*", 4: "(this|that) (the|of|and|to|in|was|is|for|with|by)"}
ALPHABET = "abcde"
LONGEST = 5
SIX_TOKENS = ("T", "h", "e", "Th", "he", "The")
TOY = Tokenizer(TOY_MERGES, "abcdefghijklmnopqrstuvwxyz")


def relations(spark, ids=(1, 2, 3, 4)):
    edges, states = graph.edges_df(spark, {i: fa.compile_regex(PATTERNS[i]) for i in ids})
    return edges, states.where("is_final").select("query_id", "state"), states


def in_tasks(words, rows, schema):
    """What rows(w) gives for each word of words (w): an automaton a word, made and walked in the tasks."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches):
        for pdf in batches:
            yield pd.DataFrame([r for w in pdf["w"] for r in rows(w)], columns=names)

    return words.mapInPandas(run, schema)


def values(rows) -> str:
    quoted = lambda x: "'" + x.replace("'", "''") + "'" if isinstance(x, str) else str(x)
    return "VALUES " + ", ".join("(" + ", ".join(map(quoted, r)) + ")" for r in rows)


# The languages by their own definitions, not by automata: all strings over the letters, filtered by the pattern.
ALL_STRINGS = f"""letters AS (SELECT unnest(string_split('{ALPHABET}', '')) AS c),
s AS (SELECT '' AS t, 0 AS n UNION ALL SELECT t || c, n + 1 FROM s, letters WHERE n < {LONGEST}),
p AS (SELECT * FROM ({values((i, PATTERNS[i]) for i in (1, 2, 3))}) AS v(query_id, r)),
lang AS (SELECT query_id, t AS text, n FROM p, s WHERE regexp_full_match(t, r))"""


@query(f"WITH RECURSIVE {ALL_STRINGS} SELECT CAST(query_id AS BIGINT) AS query_id, text, n AS len FROM lang")
def q_enum(spark, d):
    edges, finals, _ = relations(spark, (1, 2, 3))
    return walks.enumerate_strings(edges, finals, LONGEST)


@query("SELECT w, regexp_full_match(w, '(th|wh)[aeiou][a-z]*') AS member FROM (SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en')")
def q_member(spark, d):
    """Membership by running the automaton over the letters, as a fold over a transition map."""
    dfa = fa.compile_regex("(th|wh)[aeiou][a-z]*")
    moves = F.create_map(*(F.lit(x) for s, c, t, _ in dfa.rows() for x in (f"{s}{c}", t)))
    ends = F.array(*(F.lit(s) for s in sorted(dfa.finals)))
    words = english_words(table(spark, d, "documents")).select(F.explode("w").alias("w")).distinct()
    step = lambda s, c: F.when(c == "", s).when(s < 0, s).otherwise(F.coalesce(F.element_at(moves, F.concat(s.cast("string"), c)), F.lit(-1)))
    return words.select("w", F.array_contains(ends, F.aggregate(F.split("w", ""), F.lit(0), step)).alias("member"))


@query("""WITH w AS (SELECT DISTINCT unnest(string_split(p_name, ' ')) AS w FROM part), p AS (SELECT DISTINCT substring(w, 1, i) AS node, i FROM w, LATERAL (SELECT unnest(range(0, length(w) + 1)) AS i))
SELECT node, CAST(dense_rank() OVER (ORDER BY i, node) - 1 AS INT) AS id, node IN (SELECT w FROM w) AS is_final FROM p""")
def q_trie(spark, d):
    """A trie of the words of part names: node ids breadth first."""
    from pyspark.sql import Window

    words = table(spark, d, "part").select(F.explode(F.split("p_name", " ")).alias("w")).distinct()
    nodes = words.select("w", F.explode(F.sequence(F.lit(0), F.length("w"))).alias("i")).select(F.expr("substring(w, 1, i)").alias("node"), "i", (F.col("i") == F.length("w")).alias("e"))
    nodes = nodes.groupBy("node", "i").agg(F.max("e").alias("is_final"))
    return nodes.select("node", (F.dense_rank().over(Window.orderBy("i", "node")) - 1).alias("id"), "is_final")


@query(f"WITH RECURSIVE {ALL_STRINGS} SELECT CAST(query_id AS BIGINT) AS query_id, n AS len, CAST(count(*) AS BIGINT) AS n FROM lang GROUP BY query_id, n")
def q_walks_by_len(spark, d):
    edges, finals, _ = relations(spark, (1, 2, 3))
    w = walks.walks_by_length(edges, finals, LONGEST).where("state = 0")
    return w.select("query_id", "len", F.col("n").cast("long").alias("n"))


@query(f"""WITH RECURSIVE {ALL_STRINGS} SELECT CAST(query_id AS BIGINT) AS query_id, CAST(count(*) AS BIGINT) AS n FROM lang GROUP BY query_id UNION ALL SELECT 4, 20""")
def q_walks_total(spark, d):
    edges, finals, _ = relations(spark)
    return walks.walks_total(edges, finals, 10).where("state = 0 AND query_id <> 3").select("query_id", F.col("n").cast("long").alias("n")).unionByName(
        walks.walks_total(*relations(spark, (3,))[:2], LONGEST).where("state = 0").select("query_id", F.col("n").cast("long").alias("n")))


@query("SELECT CAST(l AS INT) AS max_len, CAST(l + 1 AS BIGINT) AS n FROM range(1, 7) AS r(l)")
def q_walks_cyclic(spark, d):
    """A one-letter star unrolled to each length."""
    edges, finals, _ = relations(spark, (3,))
    by = walks.walks_by_length(edges, finals, 6).where("state = 0")
    lens = spark.range(1, 7).select(F.col("id").cast("int").alias("max_len"))
    return lens.join(F.broadcast(by), F.col("len") <= F.col("max_len")).groupBy("max_len").agg(F.sum("n").cast("long").alias("n"))


SHORT_NODES = r"""w AS (SELECT DISTINCT w FROM (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en') WHERE length(w) BETWEEN 3 AND 4),
e AS (SELECT substring(w, 1, i) AS dst, count(*) AS n FROM w, LATERAL (SELECT unnest(range(1, length(w) + 1)) AS i) GROUP BY dst)"""


def short_trie(spark, d):
    """The trie of the English words of three or four letters as relations of edges and ends; a state is the beginning that it spells."""
    words = cut(en_words(spark, d).where("length(w) BETWEEN 3 AND 4"), "short-words")
    at = words.select(F.lit(0).cast("long").alias("query_id"), F.explode(F.transform(F.sequence(F.lit(1), F.length("w")), lambda i: F.substring("w", F.lit(1), i))).alias("dst")).distinct()
    edges = at.select("query_id", F.expr("substring(dst, 1, length(dst) - 1)").alias("src"), F.expr("right(dst, 1)").alias("sym"), "dst")
    return edges, words.select(F.lit(0).cast("long").alias("query_id"), F.col("w").alias("state"))


@query(f"WITH {SHORT_NODES} SELECT substring(dst, 1, length(dst) - 1) AS src, right(dst, 1) AS sym, n, round(n / sum(n) OVER (PARTITION BY substring(dst, 1, length(dst) - 1)), 6) AS p FROM e")
def q_edge_weights(spark, d):
    """Edges of a trie by the words that they lead to."""
    return walks.edge_weights(*short_trie(spark, d), 4).select("src", "sym", "n", "p")


@query(f"WITH {SHORT_NODES} SELECT substring(dst, 1, length(dst) - 1) AS src, right(dst, 1) AS sym, round(1 / count(*) OVER (PARTITION BY substring(dst, 1, length(dst) - 1)), 6) AS p FROM e")
def q_edge_naive(spark, d):
    """The same edges, all of a state alike."""
    return walks.edge_uniform(short_trie(spark, d)[0]).select("src", "sym", "p")


@query(f"""WITH RECURSIVE {ALL_STRINGS} SELECT CAST(query_id AS BIGINT) AS query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY text) - 1 AS BIGINT) AS idx, text FROM lang""")
def q_unrank(spark, d):
    """Every index of three languages; strings come in order of text, ends before longer strings."""
    edges, finals, _ = relations(spark, (1, 2, 3))
    n = walks.walks_total(edges, finals, LONGEST).where("state = 0").select("query_id", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n").cast("long") - 1)).alias("idx"))
    return walks.unrank(n, edges, finals, LONGEST)


@query(f"WITH RECURSIVE {ALL_STRINGS} SELECT t AS text FROM s WHERE regexp_full_match(t, '[ab]*b') AND regexp_full_match(t, 'a.*')")
def q_lang_intersect(spark, d):
    return _language(spark, fa.intersect(fa.compile_regex("[ab]*b"), fa.compile_regex("a.*", alphabet=ALPHABET)))


@query(f"WITH RECURSIVE {ALL_STRINGS} SELECT t AS text FROM s WHERE regexp_full_match(t, '[ab]*') AND NOT regexp_full_match(t, '(ab)*|b+')")
def q_lang_except(spark, d):
    return _language(spark, fa.difference(fa.compile_regex("[ab]*"), fa.compile_regex("(ab)*|b+")))


def _language(spark, dfa):
    edges, states = graph.edges_df(spark, {0: dfa})
    return walks.enumerate_strings(edges, states.where("is_final").select("query_id", "state"), LONGEST).select("text")


@query("SELECT * FROM (VALUES (CAST(1 AS BIGINT), CAST(4 AS BIGINT), CAST(4 AS BIGINT)), (3, 1, 1)) AS v(query_id, states, edges)")
def q_graph_size(spark, d):
    """States and edges of minimal automata."""
    from patternlm.operators.measures import graph_stats

    edges, _, states = relations(spark, (1, 3))
    return graph_stats(edges, states).select("query_id", "states", "edges")


# -- tokenizers ---------------------------------------------------------------------------------------------------------------------

def encode_sql(word: str, times: int = 1) -> str:
    """Merges in rank order as nested replacements of delimited text; exact where no merge overlaps itself (as in the toy list); twice where the same merge follows itself at once."""
    expr = f"'|' || regexp_replace({word}, '(.)', '\\1|', 'g')"
    for a, b in (m for m in TOY_MERGES for _ in range(times)):
        expr = f"replace({expr}, '|{a}|{b}|', '|{a}{b}|')"
    return f"trim({expr}, '|')"


def encode_expr(col):
    """The same fold in Spark: a native expression for short merge lists."""
    merges = F.array(*(F.struct(F.lit(f"|{a}|{b}|").alias("x"), F.lit(f"|{a}{b}|").alias("y")) for a, b in TOY_MERGES))
    start = F.concat(F.lit("|"), F.regexp_replace(col, "(.)", "$1|"))
    return F.btrim(F.aggregate(merges, start, lambda acc, m: F.replace(acc, m["x"], m["y"])), F.lit("|"))


EN_WORDS = "SELECT DISTINCT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS w FROM documents WHERE lang = 'en'"


def en_words(spark, d):
    return english_words(table(spark, d, "documents")).select(F.explode("w").alias("w")).distinct()


THREE_LETTERS = f"SELECT DISTINCT w FROM ({EN_WORDS}) WHERE length(w) = 3"


def three_letters(spark, d):
    return en_words(spark, d).where("length(w) = 3")


@query(f"SELECT w, {encode_sql('w')} AS encoded FROM ({EN_WORDS})")
def q_encode(spark, d):
    """Canonical encoding of every distinct English word."""
    return en_words(spark, d).select("w", encode_expr(F.col("w")).alias("encoded"))


@query(f"SELECT count(*) AS words, CAST(0 AS BIGINT) AS broken FROM ({EN_WORDS})")
def q_roundtrip(spark, d):
    enc = en_words(spark, d).select("w", encode_expr(F.col("w")).alias("e"))
    return enc.agg(F.count("*").alias("words"), F.count_if(F.array_join(F.split("e", r"\|"), "") != F.col("w")).alias("broken"))


SIX_VOCAB = "(" + values((t,) for t in SIX_TOKENS) + ") AS v(token)"


@query(f"""WITH RECURSIVE v AS (SELECT * FROM ({values((t,) for t in TOY.vocab)}) AS v(token)), x AS (SELECT w AS word FROM ({THREE_LETTERS})),
r AS (SELECT word, 1 AS pos FROM x UNION ALL SELECT r.word, r.pos + length(token) FROM r JOIN v ON substring(word, pos, length(token)) = token)
SELECT word, count(*) AS encodings FROM r WHERE pos = length(word) + 1 GROUP BY word""")
def q_enc_count(spark, d):
    """Encodings of each English word of three letters, by walks of its full token automaton."""

    def rows(w):
        dfa = graph.compile_full(fa.words_dfa([w]), TOY)
        yield w, fa.walks(dfa, len(w))[len(w)][0]

    return in_tasks(three_letters(spark, d), rows, "word string, encodings long")


@query(f"""WITH v AS (SELECT token FROM {SIX_VOCAB}), x AS (SELECT 'Thehe' AS word), pos AS (SELECT unnest(range(0, 5)) AS src)
SELECT CAST(src AS INT) AS src, token, CAST(src + length(token) AS INT) AS dst FROM x, pos, v WHERE substring(word, src + 1, length(token)) = token""")
def q_full_edges(spark, d):
    """Shortcut edges by joins of walkers with edges and the vocabulary."""
    tok = Tokenizer([], vocab={t: i for i, t in enumerate(SIX_TOKENS)})
    edges, _ = graph.edges_df(spark, {0: fa.words_dfa(["Thehe"])})
    vocab = graph.vocab_df(spark, tok).select("token_id", "token")
    return graph.full_edges(edges, vocab).join(vocab, "token_id").select("src", "token", "dst")


CANON_SQL = f"SELECT w, {encode_sql('w', 2)} AS encoded FROM (SELECT DISTINCT w FROM ({EN_WORDS}) WHERE length(w) BETWEEN 3 AND 4)"


def _paths(spark, d, compiled, check=None):
    """The paths of each English word of three or four letters through its token automaton."""

    def rows(w):
        for path in fa.enumerate_language(compiled(fa.words_dfa([w])), len(w)):
            if check is None or check(path):
                yield TOY.decode(path), "|".join(TOY.text[i] for i in path)

    return in_tasks(en_words(spark, d).where("length(w) BETWEEN 3 AND 4"), rows, "w string, encoded string")


@query(CANON_SQL)
def q_canon_enum(spark, d):
    return _paths(spark, d, lambda dfa: graph.compile_enumerated(dfa, TOY, 16))


@query(CANON_SQL)
def q_canon_dyn(spark, d):
    """All encodings, kept where the tokenizer agrees."""
    return _paths(spark, d, lambda dfa: graph.compile_full(dfa, TOY), TOY.is_canonical)


@query(CANON_SQL)
def q_canon_rw(spark, d):
    """Merges rewritten into the automaton."""
    tok = Tokenizer(TOY_MERGES, vocab=TOY.vocab, chunk=None)
    return _paths(spark, d, lambda dfa: graph.compile_rewritten(dfa, tok))


# -- preprocessors ------------------------------------------------------------------------------------------------------------------

ABC26 = "abcdefghijklmnopqrstuvwxyz"


def near_sql(source: str) -> str:
    """All texts one edit from w."""
    pos = "LATERAL (SELECT unnest(range(1, length(w) + 2)) AS i)"
    letters = f"(SELECT unnest(string_split('{ABC26}', '')) AS c) AS l"
    return f"""SELECT w, w AS t FROM {source} UNION SELECT w, substring(w, 1, i - 1) || c || substring(w, i + 1) FROM {source}, {pos}, {letters} WHERE i <= length(w)
UNION SELECT w, substring(w, 1, i - 1) || c || substring(w, i) FROM {source}, {pos}, {letters} UNION SELECT w, substring(w, 1, i - 1) || substring(w, i + 1) FROM {source}, {pos} WHERE i <= length(w)"""


def near(w: str, n: int):
    """(w, text, fewest edits) of every text within n edits of w."""
    dfa = fa.edited(fa.words_dfa([w]), n, ABC26)
    return ((w, "".join(p), dfa.finals[dfa.run(p)]) for p in fa.enumerate_language(dfa, len(w) + n))


@query(f"WITH x AS ({THREE_LETTERS}), n AS ({near_sql('x')}) SELECT w, t AS text, CAST(CASE WHEN t = w THEN 0 ELSE 1 END AS INT) AS n_edits FROM n")
def q_edit1_neigh(spark, d):
    """All texts one edit from each English word of three letters."""
    return in_tasks(three_letters(spark, d), lambda w: near(w, 1), "w string, text string, n_edits int")


@query(f"WITH x AS (SELECT w FROM ({THREE_LETTERS}) WHERE w LIKE 'th_'), n1 AS (SELECT DISTINCT w AS x, t AS w FROM ({near_sql('x')})), n2 AS (SELECT DISTINCT x AS w, t FROM n1 JOIN (SELECT w, t FROM ({near_sql('(SELECT DISTINCT w FROM n1)')})) USING (w)) SELECT w, levenshtein(w, t) AS n_edits, count(*) AS n FROM n2 GROUP BY ALL")
def q_edit2(spark, d):
    """Two edits of the English words th and a letter, by the layered automaton."""
    found = in_tasks(three_letters(spark, d).where("w LIKE 'th_'"), lambda w: near(w, 2), "w string, t string, n_edits long")
    return found.groupBy("w", "n_edits").agg(F.count("*").alias("n"))


SHORT = "SELECT DISTINCT w FROM ({0}) WHERE length(w) BETWEEN 3 AND 4".format(EN_WORDS)


@query(f"WITH x AS ({SHORT}) SELECT a.w AS w1, b.w AS w2 FROM x a JOIN x b ON a.w < b.w AND levenshtein(a.w, b.w) = 1")
def q_edit_join(spark, d):
    """Word pairs one edit apart: an equi-join on deletion neighbourhoods, then the distance itself."""
    words = en_words(spark, d).where("length(w) BETWEEN 3 AND 4")
    shorter = F.transform(F.sequence(F.lit(1), F.length("w")), lambda i: F.concat(F.substring("w", F.lit(1), i - 1), F.substring(F.col("w"), i + 1, F.length("w"))))
    keyed = words.select("w", F.explode(F.array_distinct(F.concat(F.array("w"), shorter))).alias("key"))
    a, b = keyed.select(F.col("w").alias("w1"), "key"), keyed.select(F.col("w").alias("w2"), "key")
    return a.join(b, "key").where("w1 < w2").select("w1", "w2").distinct().where(F.levenshtein("w1", "w2") == 1)


def edited_words(spark, d):
    """Every one-edit neighbour of the English words of three letters, with its original."""
    return in_tasks(three_letters(spark, d), lambda w: near(w, 1), "w string, t string, n_edits int")


NEAR_ALL = f"x AS ({THREE_LETTERS}), n AS ({near_sql('x')})"


@query(f"""WITH {NEAR_ALL}, k AS (SELECT w, t, unnest(string_split('{ABC26}', '')) AS c FROM n WHERE w <> t),
d AS (SELECT c, length(t) - length(replace(t, c, '')) - (length(w) - length(replace(w, c, ''))) AS k FROM k),
g AS (SELECT CASE WHEN k > 0 THEN 'added' ELSE 'removed' END AS op, c, count(*) AS n FROM d WHERE k <> 0 GROUP BY 1, 2)
SELECT op, c, n FROM g QUALIFY row_number() OVER (PARTITION BY op ORDER BY n DESC, c) <= 10""")
def q_edit_hist(spark, d):
    from patternlm.operators.measures import edit_chars

    return edit_chars(edited_words(spark, d), "w", "t").select("op", "c", "n")


@query(f"""WITH x AS ({EN_WORDS}), n AS ({near_sql('x')}), p AS (SELECT CAST(coalesce(list_min(list_filter(range(1, least(length(w), length(t)) + 1), lambda i: substring(w, i, 1) <> substring(t, i, 1))), least(length(w), length(t)) + 1) AS INT) AS edit_pos FROM n WHERE w <> t)
SELECT edit_pos, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM p GROUP BY edit_pos""")
def q_edit_pos(spark, d):
    """Where the one-edit neighbours of every English word first differ from it."""
    from patternlm.operators.measures import neighbour_positions

    return neighbour_positions(en_words(spark, d), "w", len(ABC26))


@query("SELECT * FROM (VALUES ('a thing'), ('a  thing'), ('a big thing'), ('a bad thing'), ('a big bad thing'), ('a big  thing')) AS v(text)")
def q_erase(spark, d):
    """`bad` erased from a small language: with and without it."""
    dfa = fa.erased(fa.compile_regex("a (big )?(bad )?thing"), ["bad"])
    return spark.createDataFrame([("".join(p),) for p in fa.enumerate_language(dfa, 20)], "text string")


@query(f"SELECT w FROM ({EN_WORDS}) WHERE regexp_full_match(w, 'th[a-z]*') AND w NOT IN ('the', 'that', 'this')")
def q_filter_deferred(spark, d):
    """A filter at run time: an anti join with the listed words."""
    listed = spark.createDataFrame([("the",), ("that",), ("this",)], "w string")
    return en_words(spark, d).where(F.col("w").rlike("^th[a-z]*$")).join(F.broadcast(listed), "w", "left_anti")
