"""Character automata lowered to token automata: all encodings, or only canonical ones; in memory and as relations."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from patternlm.functions.automata import Dfa, enumerate_language, is_finite, minimise, size_of_finite, trim
from patternlm.functions.tokenizer import Tokenizer

EDGES = "query_id long, src int, sym string, dst int, zone string"
TOKEN_EDGES = "query_id long, src int, token_id int, token string, dst int, zone string"


def compile_full(dfa: Dfa, tokenizer: Tokenizer, seal_boundary: bool = False) -> Dfa:
    """Shortcut edges for every token that a path spells; a token with a body character is body, or forbidden across a sealed boundary."""
    out = Dfa([{} for _ in dfa.edges], dict(dfa.finals))
    for start in range(len(dfa.edges)):
        todo = [(start, tokenizer.trie, 0, 0)]
        while todo:
            at, node, n_prefix, n_body = todo.pop()
            if "" in node and (n_prefix or n_body):
                if not (seal_boundary and n_prefix and n_body):
                    out.edges[start][node[""]] = at
                    if not n_body:
                        out.prefix.add((start, node[""]))
            steps = dfa.edges[at]
            for c in steps if len(steps) < len(node) else node:
                if c and c in steps and c in node:
                    pre = (at, c) in dfa.prefix
                    todo.append((steps[c], node[c], n_prefix + pre, n_body + (not pre)))
    return trim(out)


class LazyFull:
    """compile_full, one state at a time as a search reaches it: long patterns with edits have far more edges than a search visits."""

    def __init__(self, dfa: Dfa, tokenizer: Tokenizer, seal_boundary: bool = False):
        self.dfa, self.tokenizer, self.seal, self.finals, self.prefix = dfa, tokenizer, seal_boundary, dfa.finals, set()
        self.edges, self._known = self, {}

    def __getitem__(self, start: int) -> dict[int, int]:
        if start not in self._known:
            found: dict[int, int] = {}
            todo = [(start, self.tokenizer.trie, 0, 0)]
            while todo:
                at, node, n_prefix, n_body = todo.pop()
                if "" in node and (n_prefix or n_body) and not (self.seal and n_prefix and n_body):
                    found[node[""]] = at
                    if not n_body:
                        self.prefix.add((start, node[""]))
                steps = self.dfa.edges[at]
                for c in steps if len(steps) < len(node) else node:
                    if c and c in steps and c in node:
                        pre = (at, c) in self.dfa.prefix
                        todo.append((steps[c], node[c], n_prefix + pre, n_body + (not pre)))
            self._known[start] = found
        return self._known[start]


def compile_enumerated(dfa: Dfa, tokenizer: Tokenizer, max_len: int) -> Dfa:
    """Canonical encodings of a finite language by listing it."""
    out = Dfa([{}])
    for path in enumerate_language(dfa, max_len):
        text, at, here, done = "".join(path), 0, 0, 0
        for i in tokenizer.encode(text):
            done += len(tokenizer.text[i])
            if i not in out.edges[at]:
                out.edges[at][i] = len(out.edges)
                out.edges.append({})
            zones = set()
            while here < done:
                pass_state = dfa.run(path[:here])
                zones.add(dfa.zone(pass_state, path[here]))
                here += 1
            if zones == {"prefix"}:
                out.prefix.add((at, i))
            at = out.edges[at][i]
        out.finals[at] = dfa.finals[dfa.run(path)]
    return minimise(out)


def rewritten_edges(dfa: Dfa, tokenizer: Tokenizer) -> tuple[set[tuple], dict, int]:
    """Merges applied to the automaton in rank order: edges (state, token text, state), finals, start. Tokenizers without chunks only."""
    edges = {(s, c, t) for s, out in enumerate(dfa.edges) for c, t in out.items()}
    finals, fresh = dict(dfa.finals), len(dfa.edges)
    for a, b in tokenizer.merges:
        enters = {t for _, x, t in edges if x == a}
        split = {s for s, x, _ in edges if x == b} & enters
        if not split:
            continue
        copy = {v: fresh + i for i, v in enumerate(sorted(split))}
        fresh += len(copy)
        after: dict[int, set[int]] = {}
        for s, x, t in edges:
            if x == b and s in split:
                after.setdefault(s, set()).add(t)
        new = set()
        for s, x, t in edges:
            for source in (s, copy[s]) if s in copy else (s,):
                barred = source != s
                if not (barred and x == b):
                    new.add((source, x, copy[t] if x == a and t in copy else t))
                if x == a and t in split and not (barred and a == b):
                    new |= {(source, a + b, w) for w in after[t]}
        finals |= {copy[v]: finals[v] for v in split if v in finals}
        edges = _alive(new, finals)
    return edges, finals, 0


def _alive(edges: set[tuple], finals: dict) -> set[tuple]:
    forward, seen = {0}, 0
    while len(forward) != seen:
        seen = len(forward)
        forward |= {t for s, _, t in edges if s in forward}
    back, seen = set(finals), 0
    while len(back) != seen:
        seen = len(back)
        back |= {s for s, _, t in edges if t in back}
    keep = forward & back
    return {e for e in edges if e[0] in keep and e[2] in keep}


def compile_rewritten(dfa: Dfa, tokenizer: Tokenizer) -> Dfa:
    """Canonical encodings by rewriting; a merged token that enters a split state keeps paths apart, so subsets are formed again."""
    from patternlm.functions.automata import Nfa

    edges, finals, _ = rewritten_edges(dfa, tokenizer)
    nfa, number = Nfa(), {}
    for s in sorted({0, *finals, *(x for e in edges for x in (e[0], e[2]))}):
        number[s] = nfa.state()
    nfa.start, nfa.finals = number[0], {number[s] for s in finals if s in number}
    for s, t, d in edges:
        nfa.moves[number[s]].append((tokenizer.vocab[t], number[d]))
    return minimise(nfa.determinise())


def pair_check(tokenizer: Tokenizer) -> Callable[[tuple[int, ...]], bool]:
    """Whether the last two tokens of a path can stand side by side in a canonical encoding (memoised by pair). Where chunks may depend on what
    stands around the pair (spaces, apostrophes) it can."""
    known: dict[tuple[int, int], bool] = {}

    def ok(path: tuple[int, ...]) -> bool:
        if len(path) < 2:
            return True
        pair = path[-2:]
        if pair not in known:
            text = tokenizer.decode(pair)
            first, second = (tokenizer.text[t] for t in pair)
            if not first.strip() and second.strip() == second and not any(c.isspace() or c == "'" for c in second):  # which chunk takes the space depends on what stands before it
                known[pair] = any(tokenizer.encode(left + text)[-2:] == pair for left in ("", "a", "0", ".", " ", "  ", "\n") if all(c in tokenizer.vocab for c in left))
            else:
                known[pair] = "'" in text or not first.strip() or any(c.isspace() for c in text[1:]) or tokenizer.encode(text) == pair
        return known[pair]

    return ok


def compile_canonical(dfa: Dfa, tokenizer: Tokenizer, method: str = "auto", max_len: int = 64, most: int = 1000, lazy: bool = False) -> tuple[Dfa, Callable | None]:
    """(token automaton, run-time path check or None). auto: small finite languages are listed; few merges without chunks rewritten; else checked."""
    if method == "auto":
        small = is_finite(dfa) and size_of_finite(dfa) <= most
        method = "enumerate" if small else "rewrite" if tokenizer.chunk is None and 0 < len(tokenizer.merges) <= 64 else "dynamic"
    if method == "enumerate":
        return compile_enumerated(dfa, tokenizer, len(dfa.edges)), None
    if method == "rewrite":
        return compile_rewritten(dfa, tokenizer), None
    return (LazyFull(dfa, tokenizer) if lazy else compile_full(dfa, tokenizer)), tokenizer.is_canonical


def edges_df(spark: SparkSession, dfas: dict[int, Dfa]) -> tuple[DataFrame, DataFrame]:
    """Character automata as relations: edges and states."""
    edges = [(q, s, c, t, z) for q, d in dfas.items() for s, c, t, z in d.rows()]
    states = [(q, s, s == 0, s in d.finals, d.finals.get(s)) for q, d in dfas.items() for s in range(len(d.edges))]
    return spark.createDataFrame(edges, EDGES), spark.createDataFrame(states, "query_id long, state int, is_start boolean, is_final boolean, edits int")


def token_edges_df(spark: SparkSession, dfas: dict[int, Dfa], tokenizer: Tokenizer) -> DataFrame:
    return spark.createDataFrame([(q, s, i, tokenizer.text[i], t, z) for q, d in dfas.items() for s, i, t, z in d.rows()], TOKEN_EDGES)


def full_edges(edges: DataFrame, vocab: DataFrame) -> DataFrame:
    """compile_full as a relation: walkers (start, here, spelled) join the edges, then the vocabulary's prefixes, at most longest-token rounds.

    edges (query_id, src, sym, dst, zone), vocab (token_id, token) -> (query_id, src, token_id, dst, zone). The vocabulary is broadcast
    (its size is fixed by the tokenizer); the walkers shuffle by (query_id, here).
    """
    prefixes = vocab.select(F.explode(F.transform(F.sequence(F.lit(1), F.length("token")), lambda i: F.substring("token", F.lit(1), i))).alias("spelled")).distinct()
    longest = vocab.agg(F.max(F.length("token"))).first()[0] or 0  # one number
    walkers = edges.select("query_id", F.col("src").alias("start"), F.col("src").alias("here"), F.lit("").alias("spelled"), F.lit(False).alias("body")).distinct()
    found = None
    for _ in range(longest):
        step = walkers.join(edges.withColumnRenamed("src", "here"), ["query_id", "here"])
        step = step.select("query_id", "start", F.col("dst").alias("here"), F.concat("spelled", "sym").alias("spelled"), (F.col("body") | (F.col("zone") == "body")).alias("body"))
        walkers = step.join(F.broadcast(prefixes), "spelled", "left_semi")
        hit = walkers.join(F.broadcast(vocab.withColumnRenamed("token", "spelled")), "spelled")
        hit = hit.select("query_id", F.col("start").alias("src"), "token_id", F.col("here").alias("dst"), F.when(F.col("body"), "body").otherwise("prefix").alias("zone"))
        found = hit if found is None else found.unionByName(hit)
    return found.distinct() if found is not None else edges.select("query_id", "src", F.lit(0).alias("token_id"), "dst", "zone").limit(0)


def vocab_df(spark: SparkSession, tokenizer: Tokenizer) -> DataFrame:
    return spark.createDataFrame([(i, t, len(t)) for t, i in tokenizer.vocab.items()], "token_id int, token string, n_chars int")


