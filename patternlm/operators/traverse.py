"""Traversals of a token automaton under a model: best-first, beam, and sampling. In-task versions and a joined frontier.

Best-first pops by (order cost, token ids). Costs are -log p and never fall along a path, so a completed string that leads the queue is
final: strings come in order of probability, without duplicate token tuples, until the language is exhausted. Rules apply to body tokens only;
a pruned token removes all continuations. Prefix tokens score nothing; they order the search by their model cost ("model") or not
at all ("zero"). Stop: limit, exhaustion, `max_cost`, or `max_pops` (then `truncated`; run_query and run_many set none of their own).
"""

from __future__ import annotations

import heapq
import itertools
import math
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from patternlm.functions import automata as fa
from patternlm.functions.tokenizer import BOS, EOS, Tokenizer
from patternlm.operators.graph import LazyFull, compile_canonical, compile_full, pair_check
from patternlm.operators.model import NextTokenModel
from patternlm.plans.query import PatternQuery, Rules
from patternlm.session import cut, delete, fresh_path, put

MATCHES = "query_id long, match_rank long, tokens array<int>, text string, order_cost double, logp double, prefix_text string, body_text string, is_canonical boolean, n_edits int, pops long, lookups long"


@dataclass
class Compiled:
    dfa: fa.Dfa
    check: Callable | None


def lower(query: PatternQuery, tokenizer: Tokenizer, lazy: bool = False, most: int = 1000) -> Compiled:
    """The query's token automaton; lazy ones grow as a search reaches their states. most: strings of a language whose canonical encodings are listed."""
    dfa = query.automaton(lazy=lazy and query.encoding == "all")
    if query.encoding == "all":
        return Compiled(LazyFull(dfa, tokenizer, query.seal_boundary) if lazy else compile_full(dfa, tokenizer, query.seal_boundary), None)
    return Compiled(*compile_canonical(dfa, tokenizer, most=most, lazy=lazy))


@dataclass
class Match:
    tokens: tuple[int, ...]
    order_cost: float
    logp: float
    n_prefix: int
    n_edits: int
    pops: int


class _Open:
    """An open path: a shared parent and one more token. Equal costs compare by token ids, then completions first."""

    __slots__ = ("parent", "token", "kind", "state", "score", "n_prefix")

    def __init__(self, parent: tuple[int, ...], token: int | None, kind: int, state: int, score: float, n_prefix: int):
        self.parent, self.token, self.kind, self.state, self.score, self.n_prefix = parent, token, kind, state, score, n_prefix

    @property
    def path(self) -> tuple[int, ...]:
        return self.parent if self.token is None else (*self.parent, self.token)

    def __lt__(self, other: _Open) -> bool:
        return (self.path, self.kind) < (other.path, other.kind)


MANY = 100  # tokens that end a string after a state; of more, those that can lead are kept for the next query


def leading(model: NextTokenModel, ctx: tuple, tokens: tuple[int, ...], rules: Rules, limit: int) -> list[tuple[int, float]]:
    """(token, log p) of the `limit` likeliest of the tokens, and of all that lie so near the last of them that rounding may put them before it. Kept by the
    state of the model: queries that differ in what it has forgotten ask once."""
    key = ("leading", model.state(ctx), tokens, rules, limit)
    if key not in model._cache:
        found = [(t, lp) for t, lp in zip(tokens, model.ruled(ctx, list(tokens), rules), strict=True) if lp > -math.inf]
        least = heapq.nlargest(limit, (lp for _, lp in found))[-1] - 1e-9 if found else 0.0
        model._cache[key] = [x for x in found if x[1] >= least]
        if len(model._cache) > 6000:
            model._cache.popitem(last=False)
    return model._cache[key]


def best_first(dfa: fa.Dfa, model: NextTokenModel, query: PatternQuery, check: Callable | None = None, limit: int | None = None, max_cost: float = math.inf, max_pops: float = 1_000_000, beam: int | None = None, counters: dict | None = None, pair: Callable | None = None, ahead: int = 1) -> Iterator[Match]:
    """Matches in order of probability. beam keeps only so many open paths (inexact, only on request).

    Paths that meet in a state of the automaton and of the model have the same continuations. With a limit, one that comes after `limit` paths
    which are no longer and order first can't be among the results: it is left out, so a search ends after states times limit steps, not after all encodings.
    pair: whether a path may end in its last two tokens, known of every path that passes `check`. With it paths of checked queries meet too, by their
    last token as well; should `check` then refuse one, it may have stood for others: counters["refused"] is set and the search ends.
    ahead: a model that computes batches is asked for the contexts of so many of the cheapest open paths at once (the order stays).
    """
    heap: list[tuple[float, _Open]] = [(0.0, _Open((), None, 1, 0, 0.0, 0))]
    pops = found = 0
    counters = {} if counters is None else counters
    merge = bool(limit) and (check is None or pair is not None) and beam is None
    met: dict[tuple, list[tuple[float, int]]] = {}  # (state, model state) -> cost and length of the paths expanded there
    best: dict[tuple, tuple[float, int]] = {}  # of one result: the cheapest path that waits or was expanded there
    tail = model.order - 1
    parts: dict[int, tuple] = {}
    few = merge and check is None and not query.require_eos

    def split(state: int) -> tuple[dict, list[int], list[int], tuple[int, ...]]:
        """Edges of a state, its body tokens, its prefix tokens, and (taken from the first, where a limit makes most of them needless) many body tokens that end a string."""
        if state not in parts:
            edges = dfa.edges[state]
            tokens = sorted(edges)
            body = [t for t in tokens if (state, t) not in dfa.prefix]
            ends = tuple(t for t in body if edges[t] in dfa.finals) if few and len(body) > MANY else ()
            if len(ends) <= max(MANY, limit or 0):
                ends = ()
            parts[state] = edges, [t for t in body if edges[t] not in dfa.finals] if ends else body, [t for t in tokens if (state, t) in dfa.prefix], ends
        return parts[state]

    def push(cost: float, ctx: tuple, path: tuple, t: int, to: int, score: float, n_prefix: int) -> None:
        if pair and not pair((*path[-1:], t)):
            return
        if merge and limit == 1:
            key = (to, t if pair else None, model.state((*(ctx[-tail:] if tail > 0 else ()), t)))
            known = best.get(key)
            if known and known[0] < cost and known[1] <= len(path) + 1:
                return
            if not known or cost < known[0]:
                best[key] = (cost, len(path) + 1)
        heapq.heappush(heap, (cost, _Open(path, t, 1, to, score, n_prefix)))

    while heap and pops < max_pops:
        cost, at = heapq.heappop(heap)
        path, state, score, n_prefix = at.path, at.state, at.score, at.n_prefix
        if cost > max_cost:
            break
        ctx = (BOS, *path)
        if at.kind and merge:
            before = met.setdefault((state, ctx[-1] if pair else None, model.state(ctx)), [])
            if len(before) >= limit and sum(c < cost and n <= len(path) or c == cost and n == len(path) for c, n in before) >= limit:
                continue
            before.append((cost, len(path)))
        pops += 1
        if at.kind == 0:
            if check is None or check(path):
                counters["pops"] = pops
                yield Match(path, cost, -score, n_prefix, dfa.finals[state], pops)
                found += 1
                if limit and found >= limit:
                    return
            elif merge:
                counters["refused"] = True
                return
            continue
        if state in dfa.finals:
            end = -model.ruled(ctx, [EOS], Rules())[0] if query.require_eos else 0.0
            if end < math.inf:
                heapq.heappush(heap, (cost + end, _Open(path, None, 0, state, score + end, n_prefix)))
        if len(path) >= query.max_tokens or not dfa.edges[state]:
            continue
        if ahead > 1 and not model.holds(ctx):
            model.prefetch([ctx, *((BOS, *x.path) for _, x in heapq.nsmallest(ahead - 1, heap) if x.kind)])
        edges, body, prefix, ends = split(state)
        if ends:  # each is a result: only the `limit` first of them, and what follows them, can be among the results
            first = heapq.nsmallest(limit, ((cost - lp, t, lp) for t, lp in leading(model, ctx, ends, query.rules, limit)))
            for _, t, lp in first:
                push(cost - lp, ctx, path, t, edges[t], score - lp, n_prefix)
        for t, lp in zip(body, model.ruled(ctx, body, query.rules), strict=True) if body else ():
            if lp > -math.inf:
                push(cost - lp, ctx, path, t, edges[t], score - lp, n_prefix)
        if prefix:
            costs = model.ruled(ctx, prefix, Rules()) if query.prefix_order == "model" else [0.0] * len(prefix)
            for t, lp in zip(prefix, costs, strict=True):
                push(cost - (lp if lp > -math.inf else -700.0), ctx, path, t, edges[t], score, n_prefix + 1)
        if beam and len(heap) > beam:
            heap = heapq.nsmallest(beam, heap)
            heapq.heapify(heap)
    counters["pops"] = pops
    counters["truncated"] = bool(heap) and pops >= max_pops


def best_listed(dfa: fa.Dfa, model: NextTokenModel, query: PatternQuery, tokenizer: Tokenizer, limit: int | None = None) -> Iterator[Match]:
    """The canonical matches of a finite language of characters, best first, by scoring every string of it: one encoding each, so nothing is searched."""
    cut_off = -700.0
    last: list[int] = []  # tokens of the string before, and (order cost, score, prefix tokens) after each: neighbours share their beginnings
    sums: list[tuple[float, float, int]] = [(0.0, 0.0, 0)]
    rows, n = [], 0
    for letters in fa.enumerate_language(dfa, len(dfa.edges)):
        n += 1
        ids = tokenizer.encode("".join(letters))
        if len(ids) > query.max_tokens:
            continue
        same = 0
        while same < min(len(ids), len(last)) and ids[same] == last[same]:
            same += 1
        del sums[same + 1 :]
        zones, state = [], 0
        for c in letters:
            zones.append((state, c) in dfa.prefix)
            state = dfa.edges[state][c]
        at = sum(len(tokenizer.text[t]) for t in ids[: len(sums) - 1])
        for i in range(len(sums) - 1, len(ids)):
            cost, score, n_prefix = sums[-1]
            width = len(tokenizer.text[ids[i]])
            head = all(zones[at : at + width])
            at += width
            lp = model.ruled((BOS, *ids[:i]), [ids[i]], Rules() if head else query.rules)[0]
            if head:
                lp = (lp if lp > -math.inf else cut_off) if query.prefix_order == "model" else 0.0
                sums.append((cost - lp, score, n_prefix + 1))
            elif lp > -math.inf:
                sums.append((cost - lp, score - lp, n_prefix))
            else:
                break
        last = list(ids[: len(sums) - 1])
        if len(last) < len(ids):
            continue
        cost, score, n_prefix = sums[-1]
        end = -model.ruled((BOS, *ids), [EOS], Rules())[0] if query.require_eos else 0.0
        if end < math.inf:
            rows.append((cost + end, ids, score + end, n_prefix, dfa.finals[state]))
    for cost, ids, score, n_prefix, edits in heapq.nsmallest(limit, rows) if limit else sorted(rows):
        yield Match(ids, cost, -score, n_prefix, edits, n)


def any_match(dfa: fa.Dfa, model: NextTokenModel, query: PatternQuery, check: Callable | None = None, pair: Callable | None = None) -> bool | None:
    """Whether best_first would find a match: a walk over the states of automaton and model, the last tokens first, without probabilities of prefixes or an order.

    A state is walked on from again only with fewer tokens. Of the context counts what a rule can still ask for: where no body token leaves within k prefix
    tokens, the last order - 1 - k tokens, so far from the body a state of the automaton is walked on from once. pair: as in best_first; None where `check`
    refused a path that may have stood for others.
    """
    tail, near, met, refused = model.order - 1, {}, {}, False
    parts: dict[int, tuple[dict, list[int], list[int]]] = {}

    def split(state: int) -> tuple[dict, list[int], list[int]]:
        """Edges of a state, the tokens of the body among them, and those of the prefix."""
        if state not in parts:
            edges = dfa.edges[state]
            body = [t for t in edges if (state, t) not in dfa.prefix]
            parts[state] = edges, body, [t for t in edges if (state, t) in dfa.prefix] if len(body) < len(edges) else []
        return parts[state]

    def away(state: int, most: int) -> int:
        """Prefix tokens until a body token may leave, `most` where none does before."""
        if most <= 0:
            return 0
        if (state, most) not in near:
            edges, body, prefix = split(state)
            near[state, most] = 0 if body or state in dfa.finals else min((1 + away(to, most - 1) for to in {edges[t] for t in prefix}), default=most)
        return near[state, most]

    todo: list[tuple] = [(None, (BOS,), 0, 0)]  # (tokens as a linked list, context, state, number of tokens)
    while todo:
        path, ctx, state, n = todo.pop()
        if state in dfa.finals and (not query.require_eos or model.ruled(ctx, [EOS], Rules())[0] > -math.inf):
            if check is None:
                return True
            tokens, at = [], path
            while at:
                at, t = at
                tokens.append(t)
            if check(tuple(reversed(tokens))):
                return True
            refused = True
        if n >= query.max_tokens:
            continue
        edges, body, prefix = split(state)
        if pair and path:
            body, prefix = ([t for t in ts if pair((path[1], t))] for ts in (body, prefix))
        if body:
            body = [t for t, lp in zip(body, model.ruled(ctx, body, query.rules), strict=True) if lp > -math.inf]
        for t in itertools.chain(prefix, body):
            to = edges[t]
            after = (*ctx, t)[-max(tail, 1) :]
            left = tail - away(to, tail)
            key = (to, t if pair else None, model.state(after[len(after) - left :] if left < len(after) else after))
            if n + 1 < met.get(key, math.inf):
                met[key] = n + 1
                todo.append(((path, t), after, to, n + 1))
    return None if refused else False


def uniform(seed: int, sample: int, step: int) -> float:
    """A number in [0, 1) that depends on its arguments alone (a published 64-bit mixer)."""
    x = (seed * 0x9E3779B97F4A7C15 + sample * 0xBF58476D1CE4E5B9 + step * 0x94D049BB133111EB + 0x2545F4914F6CDD1D) & (2**64 - 1)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = ((x ^ (x >> shift)) * factor) & (2**64 - 1)
    return ((x ^ (x >> 31)) >> 11) / 2**53


@dataclass
class Sample:
    tokens: tuple[int, ...]
    n_prefix: int
    logp: float
    weight: float
    accepted: bool
    n_edits: int


class Sampler:
    """Prefix tokens by walk counts (uniform over prefixes) or by edges (biased; for comparison), then body tokens by the model.

    masked: renormalised over allowed tokens, weight = the mass allowed; reject: drawn from the rules-limited model, dead draws not accepted;
    exact: tokens weighted by their accepted mass (models with bounded contexts). A final state stops with the end token's probability where the
    query requires it. Elsewhere the language goes on from some final states, and stopping is a choice of its own: exact draws stop with
    1/mass, so a string's share is its probability among all strings of the language; masked and rejected draws stop with 1/walks, one of the strings that
    begin here, and weigh by the inverse of what they chose. check: whether a whole path counts (canonical encodings); pair: whether a path may end
    in its last two tokens; draws that fail are repeated, `tries` times at most, then not accepted.
    """

    def __init__(self, dfa: fa.Dfa, model: NextTokenModel, query: PatternQuery, mode: str = "masked", weights: str = "walks", check: Callable | None = None, pair: Callable | None = None, tries: int = 100):
        self.check, self.pair, self.tries = check, pair, tries
        self.dfa, self.model, self.query, self.mode, self.weights = dfa, model, query, mode, weights
        self.heads = self._prefix_part()
        self.counts = fa.walks(self.heads, query.max_tokens)
        self._mass: dict = {}
        self._strings: list[list[int]] | None = None

    def strings(self, state: int, left: int) -> int:
        """How many strings of the language begin in this state, the empty one included."""
        if self._strings is None:
            d = self.dfa
            self._strings = fa.walks(fa.Dfa([{t: n for t, n in out.items() if (s, t) not in d.prefix} for s, out in enumerate(d.edges)], d.finals), self.query.max_tokens)
        return max(1, self._strings[left][state])

    def _prefix_part(self) -> fa.Dfa:
        """The automaton of prefixes: prefix edges, ending where a body edge leaves or the language ends."""
        d = self.dfa
        edges = [{t: n for t, n in out.items() if (s, t) in d.prefix} for s, out in enumerate(d.edges)]
        finals = {s: 0 for s, out in enumerate(d.edges) if s in d.finals or len(edges[s]) < len(out)}
        return fa.Dfa(edges, finals)

    def mass(self, state: int, ctx: tuple, left: int) -> float:
        """Accepted probability from here (body only)."""
        key = (state, self.model.state(ctx), left)
        if key not in self._mass:
            total = 0.0
            if state in self.dfa.finals:
                total += math.exp(self.model.logp(ctx, EOS)) if self.query.require_eos else 1.0
            if left:
                tokens = sorted(t for t in self.dfa.edges[state] if (state, t) not in self.dfa.prefix)
                for t, lp in zip(tokens, self.model.ruled(ctx, tokens, self.query.rules), strict=True) if tokens else ():
                    if lp > -math.inf:
                        total += math.exp(lp) * self.mass(self.dfa.edges[state][t], (*ctx, t), left - 1)
            self._mass[key] = total
        return self._mass[key]

    def draw(self, sample_id: int) -> Sample:
        for i in range(self.tries):
            s = self._draw(sample_id, i << 20)
            if self.check is None or not s.accepted or self.check(s.tokens):
                break
        else:
            s.accepted, s.weight = False, 0.0
        return s

    def _draw(self, sample_id: int, first: int) -> Sample:
        q, d, path, state, logp, weight, step, n_prefix = self.query, self.dfa, (), 0, 0.0, 1.0, first, 0
        rand = lambda: uniform(q.seed, sample_id, step)
        prefix = self.heads if d.prefix else None
        left = q.max_tokens
        while prefix is not None and prefix.edges[state]:
            tokens = sorted(prefix.edges[state])
            stop = int(state in prefix.finals)
            w = [self.counts[left - 1][prefix.edges[state][t]] if self.weights == "walks" else 1 for t in tokens] if left else []
            total = sum(w) + stop
            if total == 0:
                break
            u, step = rand() * total, step + 1
            if u < stop:
                break
            u -= stop
            for t, x in zip(tokens, w, strict=True):
                if u < x:
                    break
                u -= x
            path, state, left, n_prefix = (*path, t), prefix.edges[state][t], left - 1, n_prefix + 1
        while True:
            ctx = (BOS, *path)
            out = {t: n for t, n in d.edges[state].items() if (state, t) not in d.prefix and (self.pair is None or self.pair((*path[-1:], t)))}
            tokens = sorted(out)
            final = state in d.finals
            if final and not q.require_eos:
                if not left or not out:
                    return Sample(path, n_prefix, logp, weight, True, d.finals[state])
                stop = 1 / (self.mass(state, ctx, left) if self.mode == "exact" else self.strings(state, left))
                u, step = rand(), step + 1
                if u < stop:
                    return Sample(path, n_prefix, logp, weight if self.mode == "exact" else weight / stop, True, d.finals[state])
                weight /= 1.0 if self.mode == "exact" else 1 - stop
            if not left:
                return Sample(path, n_prefix, logp, weight, False, 0)
            choices = [*tokens, *([EOS] if final and q.require_eos else [])]
            lps = (self.model.ruled(ctx, tokens, q.rules) if tokens else []) + ([self.model.logp(ctx, EOS)] if final and q.require_eos else [])
            ps = [math.exp(x) if x > -math.inf else 0.0 for x in lps]
            if self.mode == "exact":
                ps = [p * (1.0 if t == EOS else self.mass(out[t], (*ctx, t), left - 1)) for t, p in zip(choices, ps, strict=True)]
            total = sum(ps)
            if total <= 0:
                return Sample(path, n_prefix, logp, 0.0, False, 0)
            u, step = rand(), step + 1
            if self.mode == "reject":
                if u >= total:
                    return Sample(path, n_prefix, logp, 0.0, False, 0)
            else:
                weight *= total if self.mode == "masked" else 1.0
                u *= total
            for t, p, lp in zip(choices, ps, lps, strict=True):
                if u < p:
                    break
                u -= p
            else:
                t, lp = next((t, lp) for t, p, lp in reversed(list(zip(choices, ps, lps, strict=True))) if p > 0)
            logp += lp
            if t == EOS:
                return Sample(path, n_prefix, logp, weight, True, d.finals[state])
            path, state, left = (*path, t), out[t], left - 1


def row_of(query_id: int, rank: int, m: Match, tokenizer: Tokenizer, model: NextTokenModel, canonical: bool | None = None) -> tuple:
    text, head = tokenizer.decode(m.tokens), tokenizer.decode(m.tokens[: m.n_prefix])
    return (query_id, rank, list(m.tokens), text, m.order_cost, m.logp, head, text[len(head) :], tokenizer.is_canonical(m.tokens) if canonical is None else canonical, m.n_edits, m.pops, model.lookups)


def _matches(query: PatternQuery, model: NextTokenModel, tokenizer: Tokenizer, limit: int | None, **options) -> Iterator[Match]:
    """Matches until the limit or the end of the language. Canonical queries whose encodings were not listed leave out paths with a pair of tokens
    that no canonical encoding has; if that is not enough, the strings themselves are listed."""
    compiled = lower(query, tokenizer, lazy=True)
    options = {"max_pops": math.inf} | options
    if compiled.check is None or not limit or options.get("beam"):
        yield from best_first(compiled.dfa, model, query, compiled.check, limit, **options)
        return
    counters = options.setdefault("counters", {})
    found = list(best_first(compiled.dfa, model, query, compiled.check, limit, pair=pair_check(tokenizer), **options))
    if counters.pop("refused", False):
        dfa = query.automaton()
        found = best_listed(dfa, model, query, tokenizer, limit) if fa.is_finite(dfa) else best_first(compiled.dfa, model, query, compiled.check, limit, **options)
    yield from found


def _beam(query, model, tokenizer, limit, beam: int = 64, **options) -> Iterator[Match]:
    return _matches(query, model, tokenizer, limit, beam=beam, **options)


def _draws(query, model, tokenizer, limit, mode: str = "exact", weights: str = "walks", **_) -> Iterator[Match]:
    """`limit` accepted samples (without a limit: endlessly), repeated ones included."""
    compiled = lower(query, tokenizer)
    sampler = Sampler(compiled.dfa, model, query, mode, weights, compiled.check, pair_check(tokenizer) if compiled.check else None)
    found = 0
    for i in itertools.count():
        if limit and found >= limit:
            return
        s = sampler.draw(i)
        if s.accepted:
            found += 1
            yield Match(s.tokens, -s.logp, s.logp, s.n_prefix, s.n_edits, i + 1)


# A traversal takes (query, model, tokenizer, limit, **options) and yields matches; PatternQuery.traversal names it.
TRAVERSALS: dict[str, Callable[..., Iterator[Match]]] = {"best": _matches, "beam": _beam, "sample": _draws}


def register_traversal(name: str, traversal: Callable[..., Iterator[Match]]) -> None:
    """Make a traversal of one's own available to queries (on the driver; tasks get it with the module that registers it)."""
    TRAVERSALS[name] = traversal


def run_query(query: PatternQuery, model: NextTokenModel, tokenizer: Tokenizer, limit: int | None = None, query_id: int = 0, distinct_on: str = "tokens", **options) -> list[tuple]:
    """Rows of MATCHES of one query. distinct_on="text" keeps the best encoding of each string."""
    own = None if distinct_on == "text" or query.deferred_words else limit
    rows, seen = [], set()
    if query.traversal not in TRAVERSALS:
        raise ValueError(f"no traversal {query.traversal!r}; known: {', '.join(TRAVERSALS)}")
    for m in TRAVERSALS[query.traversal](query, model, tokenizer, own, **options):
        row = row_of(query_id, len(rows) + 1, m, tokenizer, model)
        if row[7] in query.deferred_words or (distinct_on == "text" and row[3] in seen):
            continue
        seen.add(row[3])
        rows.append(row)
        if limit and len(rows) >= limit:
            break
    return rows


def iterate(query: PatternQuery, model: NextTokenModel, tokenizer: Tokenizer, **options) -> Iterator[Match]:
    """A lazy stream of matches on the driver."""
    compiled = lower(query, tokenizer, lazy=True)
    yield from best_first(compiled.dfa, model, query, compiled.check, **options)


def tasks(spark: SparkSession) -> int:
    """Into how many tasks searches are dealt: given as a number, else adaptive execution joins them into one, because their rows are few bytes."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism)


def run_many(spark: SparkSession, queries: DataFrame, build: Callable[[dict], PatternQuery], model: NextTokenModel, tokenizer: Tokenizer, limit: int | None = 1, **options) -> DataFrame:
    """Matches of one query for each row of queries (query_id and whatever build reads): whole searches inside tasks.

    The model is packed (checked at packing) and broadcast once; queries spread over tasks by id. No state crosses tasks, so lost tasks are just run again.
    """
    shared = spark.sparkContext.broadcast((model, tokenizer))

    def run(batches):
        m, t = shared.value
        for pdf in batches:
            rows = [r for q in pdf.to_dict("records") for r in run_query(build(q), m, t, limit, q["query_id"], **options)]
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in MATCHES.split(", ")])

    return queries.repartition(tasks(spark), "query_id").mapInPandas(run, MATCHES)


def count_matches(dfa: fa.Dfa, model: NextTokenModel, query: PatternQuery) -> dict[int, int]:
    """Matches of a query over all encodings by their fewest edits, however many there are: paths are added up where they meet in a state of automaton and model, token by token, and never listed."""
    onward: dict[tuple, list[tuple]] = {}
    out: dict[int, int] = {}
    level = {(0, model.state((BOS,))): 1}
    for n in range(query.max_tokens + 1):
        following: dict[tuple, int] = {}
        for at, paths in level.items():
            state, ctx = at
            if state in dfa.finals and (not query.require_eos or model.ruled(ctx, [EOS], Rules())[0] > -math.inf):
                out[dfa.finals[state]] = out.get(dfa.finals[state], 0) + paths
            if n == query.max_tokens:
                continue
            if at not in onward:
                edges = dfa.edges[state]
                body = [t for t in edges if (state, t) not in dfa.prefix]
                kept = [t for t, lp in zip(body, model.ruled(ctx, body, query.rules), strict=True) if lp > -math.inf] if body else []
                kept += [t for t in edges if (state, t) in dfa.prefix]
                onward[at] = [(edges[t], model.state((*ctx, t))) for t in kept]
            for to in onward[at]:
                following[to] = following.get(to, 0) + paths
        level = following
        if not level:
            break
    return out


def counted(spark: SparkSession, queries: DataFrame, build: Callable[[dict], PatternQuery], model: NextTokenModel, tokenizer: Tokenizer) -> DataFrame:
    """(query_id, n, plain) of each row of queries: all matches over all encodings, and those without an edit that are canonical."""
    shared = spark.sparkContext.broadcast((model, tokenizer))

    def run(batches):
        m, t = shared.value
        for pdf in batches:
            rows = []
            for row in pdf.to_dict("records"):
                q = build(row)
                found = count_matches(lower(q, t, lazy=True).dfa, m, q)
                plain = q.but(encoding="canonical", preprocessors=tuple(p for p in q.preprocessors if p.kind != "edits"))
                if found:
                    rows.append((row["query_id"], sum(found.values()), len(run_query(plain, m, t)) if found.get(0) else 0))
            yield pd.DataFrame(rows, columns=["query_id", "n", "plain"])

    return queries.repartition(tasks(spark), "query_id").mapInPandas(run, "query_id long, n long, plain long")


def extractable(queries: Sequence[PatternQuery], models: Sequence[NextTokenModel], tokenizer: Tokenizer, pair: Callable) -> list[list[bool]]:
    """For each query and model whether run_query finds a match. Queries that differ in their encodings alone follow one another, canonical first: they share an
    automaton, and what has a canonical match has one among all encodings. pair: a pair_check, shared so that it is asked once for each pair."""
    out: list[list[bool]] = []
    last, compiled = None, None
    for q in queries:
        again = last is not None and last.but(encoding=q.encoding) == q and q.encoding == "all" and not q.seal_boundary and compiled.check is not None
        compiled = Compiled(compiled.dfa, None) if again else lower(q, tokenizer, lazy=True)
        known = out[-1] if again else [False] * len(models)
        found = []
        for model, yes in zip(models, known, strict=True):
            any_ = yes or any_match(compiled.dfa, model, q, compiled.check, pair if compiled.check else None)
            found.append(bool(run_query(q, model, tokenizer, 1)) if any_ is None else any_)
        out.append(found)
        last = q
    return out


def successes(spark: SparkSession, queries: DataFrame, build: Callable[[dict], Sequence[PatternQuery]], models: Sequence[NextTokenModel], tokenizer: Tokenizer) -> DataFrame:
    """(query_id, setting, model) of each row of queries, place of its queries and place of a model where run_many would give a match."""
    shared = spark.sparkContext.broadcast((models, tokenizer))

    def run(batches):
        ms, t = shared.value
        pair = pair_check(t)
        for pdf in batches:
            rows = [(q["query_id"], i, j) for q in pdf.to_dict("records") for i, found in enumerate(extractable(build(q), ms, t, pair)) for j, yes in enumerate(found) if yes]
            yield pd.DataFrame(rows, columns=["query_id", "setting", "model"])

    return queries.repartition(tasks(spark), "query_id").mapInPandas(run, "query_id long, setting int, model int")


def derive(matches: DataFrame, **columns) -> DataFrame:
    """The matches of one round of queries as the queries of the next: columns are expressions over MATCHES; ids are (query_id, match_rank) hashed."""
    own = {"query_id": F.xxhash64("query_id", "match_rank")} | columns
    return matches.select(*(c.alias(name) for name, c in own.items()))


SAMPLES = "sample_id long, tokens array<int>, text string, prefix_text string, body_text string, logp double, weight double, accepted boolean, is_canonical boolean, n_edits int"


LISTED = 50_000  # a language of so many strings is sampled from the list of its canonical encodings, so no draw fails


def sample(spark: SparkSession, query: PatternQuery, model: NextTokenModel, tokenizer: Tokenizer, n: int, mode: str = "masked", weights: str = "walks") -> DataFrame:
    """n samples of a query, by id: the same on every rerun and partitioning."""
    compiled = lower(query, tokenizer, most=LISTED)
    shared = spark.sparkContext.broadcast((model, tokenizer, compiled.dfa))
    checked = compiled.check is not None

    def run(batches):
        m, t, dfa = shared.value
        sampler = Sampler(dfa, m, query, mode, weights, t.is_canonical if checked else None, pair_check(t) if checked else None)
        for pdf in batches:
            rows = []
            for i in pdf["id"]:
                s = sampler.draw(int(i))
                text, head = t.decode(s.tokens), t.decode(s.tokens[: s.n_prefix])
                rows.append((int(i), list(s.tokens), text, head, text[len(head) :], s.logp, s.weight, s.accepted, t.is_canonical(s.tokens), s.n_edits))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in SAMPLES.split(", ")])

    return spark.range(n).mapInPandas(run, SAMPLES)


FRONTIER = ("query_id", "node", "ctx", "tokens", "order_cost", "score")


def frontier_search(token_edges: DataFrame, finals: DataFrame, arcs: DataFrame, top_k: int | None, limit: int, batch: int = 512, max_rounds: int | None = None, prefix_order: str = "model", start_ctx: str = str(BOS), max_cost: float | None = None) -> DataFrame:
    """Best-first for many queries at once as joins, for models and automata that are too large for a task.

    Relations: token_edges (query_id, src, token_id, dst, zone), finals (query_id, state), arcs (ctx, tok, p, rnk, nxt). Each round pops the
    cheapest `batch` open paths of every query, joins edges and arcs, drops what rules forbid, and settles: a completed string is emitted once it is
    strictly cheaper than every open path of its query. Rounds go on until every query has `limit` settled strings or no open path;
    where `max_rounds` ends them earlier, `truncated` says so. arcs must hold the arcs of prefix tokens, which no rule cuts (its `always`).

    The cheapest paths are ranked by a window whose limit Spark applies in each input task (batch up to its group limit threshold, 1000), so at most
    tasks x batch paths of a query meet in one; the others are compared with the last popped one and never sorted. Popped paths are written
    once, to a folder a round, and the old frontier is deleted. Only whether a query is still open reaches the driver.
    """
    spark = token_edges.sparkSession
    start = token_edges.select("query_id").distinct().select("query_id", F.lit(0).alias("node"), F.lit(start_ctx).alias("ctx"), F.array().cast("array<int>").alias("tokens"), F.lit(0.0).alias("order_cost"), F.lit(0.0).alias("score"))
    folder, at = fresh_path(spark, "popped"), fresh_path(spark, "frontier")
    open_, keep, rounds, truncated = put(start, at), None, [], False
    ends = finals.select("query_id", F.col("state").alias("node"))
    by_cost = Window.partitionBy("query_id").orderBy("order_cost", "tokens")
    place = F.struct("order_cost", "tokens")
    while True:
        alive = open_ if keep is None else open_.join(keep, "query_id", "left_semi")
        rounds.append(f"{folder}/{len(rounds)}")
        popped = put(alive.withColumn("place", F.row_number().over(by_cost)).where(F.col("place") <= batch).drop("place"), rounds[-1])
        last = popped.groupBy("query_id").agg(F.max(place).alias("last"))
        rest = alive.join(last, "query_id").where(place > F.col("last")).drop("last")
        step = popped.join(token_edges.withColumnRenamed("src", "node"), ["query_id", "node"])
        step = step.join(arcs.select("ctx", F.col("tok").alias("token_id"), "p", "rnk", "nxt"), ["ctx", "token_id"])
        body = F.col("zone") == "body"
        if top_k:
            step = step.where(~body | (F.col("rnk") <= top_k))
        cost = -F.log("p")
        order = cost if prefix_order == "model" else F.when(body, cost).otherwise(0.0)
        grown = step.select("query_id", F.col("dst").alias("node"), F.col("nxt").alias("ctx"), F.concat("tokens", F.array(F.col("token_id"))).alias("tokens"), (F.col("order_cost") + order).alias("order_cost"), (F.col("score") + F.when(body, cost).otherwise(0.0)).alias("score"))
        if max_cost is not None:
            grown = grown.where(F.col("order_cost") <= max_cost)
        before, at = at, fresh_path(spark, "frontier")
        open_ = put(rest.unionByName(grown), at)
        delete(spark, before)
        done = spark.read.schema(popped.schema).parquet(*rounds).join(ends, ["query_id", "node"], "left_semi")
        least = open_.groupBy("query_id").agg(F.min("order_cost").alias("least"))
        settled = done.join(least, "query_id").groupBy("query_id").agg(F.count_if(F.col("order_cost") < F.col("least")).alias("n"))
        keep = cut(least.join(settled, "query_id", "left").where(F.coalesce("n", F.lit(0)) < limit).select("query_id"), "open")
        if keep.isEmpty():
            break
        if max_rounds and len(rounds) >= max_rounds:
            truncated = True
            break
    out = done.withColumn("match_rank", F.row_number().over(by_cost)).where(F.col("match_rank") <= limit)
    return out.select("query_id", F.col("match_rank").cast("long").alias("match_rank"), "tokens", "order_cost", (-F.col("score")).alias("logp"), F.lit(truncated).alias("truncated"))
