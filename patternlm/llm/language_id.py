"""Language identification by prediction by partial matching.

A byte context tree per language (contexts of 0 to `order` bytes, kept where the training sample has them at least twice) with escape
method C: a context with n occurrences of q distinct followers gives a follower seen c times c/(n+q) and escapes with q/(n+q) to the
next shorter context, where followers already covered are excluded; below the empty context all bytes are alike. Statistics
are frozen after training, so the code length of every (context, byte) is a constant: all trees share one table of them, and a text's
exact code length in each language is the sum over its bytes, of which there is one lookup each.

Training rows are a bounded sample: at most `per_language` documents of each language, of at most LONGEST characters each, those with the lowest
hashes of their ids among the rows that the caller offers; nothing else of the rows reaches the driver. The trees of all languages are shipped
to the tasks: some 20 MB a language at order 3, which suits tens of languages, not thousands. Texts are lower-cased. A null text or one without a letter is `und` with score 0, as is everything when nothing could be
learned; otherwise the score is the posterior of the best language under equal priors (ties: the first language by code point).
Empty tables give empty results; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from patternlm.llm.common import column, crc_mod
from patternlm.llm.text_kernel import slices, text_buffers

PER_LANGUAGE = 400
LONGEST = 100_000  # characters of a training text, at most
ORDER = 3
SALTS = 32


class ContextTrees(NamedTuple):
    languages: list[str]
    symbols: np.ndarray  # byte -> symbol; the last symbol stands for bytes that training lacks
    size: int  # symbols
    deepest: np.ndarray  # coded last `order` symbols -> node
    bits: np.ndarray  # (node * size + symbol, language) -> code length
    order: int


def _contexts(stream: np.ndarray, size: int, order: int) -> list[np.ndarray]:
    """For each position the coded contexts of 0..order symbols (stream starts with `order` pads)."""
    n = len(stream) - order
    out, code = [np.zeros(n, np.int64)], np.zeros(n, np.int64)
    for d in range(1, order + 1):
        code = code + stream[order - d : order - d + n] * size ** (d - 1)
        out.append(code)
    return out


def train(samples: dict[str, list[bytes]], order: int = ORDER, least: int = 2) -> ContextTrees:
    """Context trees of the languages of samples (lower-cased texts in UTF-8)."""
    languages = sorted(samples)
    seen = sum((np.bincount(np.frombuffer(b"".join(samples[x]) + b"\n", np.uint8), minlength=256) for x in languages), np.zeros(256, np.int64))
    known = np.flatnonzero(seen)
    size = len(known) + 1
    symbols = np.full(256, size - 1, np.int64)
    symbols[known] = np.arange(len(known))
    pad = np.full(order, symbols[10], np.int64)
    counts = []  # by language and depth: context codes, followers, counts
    for x in languages:
        depth = [[] for _ in range(order + 1)]
        for text in samples[x]:
            stream = np.concatenate([pad, symbols[np.frombuffer(text, np.uint8)]])
            for d, code in enumerate(_contexts(stream, size, order)):
                depth[d].append(code * size + stream[order:])
        counts.append([np.unique(np.concatenate([*c, np.zeros(0, np.int64)]), return_counts=True) for c in depth])
    rows = {0: np.full((1, size, len(languages)), 1.0 / 256)}
    rows[0][:, -1, :] = (256 - len(known)) / 256 if len(known) < 256 else 1e-9
    base, deepest, node_rows, codes = rows[0], np.zeros(size**order, np.int32), [], [np.zeros(1, np.int64)]
    offset, parent_rows, parent_index = 0, base, {0: 0}
    for d in range(order + 1):
        if d == 0:
            nodes = np.zeros(1, np.int64)
        else:
            held = [np.unique(c[d][0] // size, return_inverse=True) for c in counts]
            totals = [np.bincount(inv, weights=c[d][1]) if len(ctx) else np.zeros(0) for (ctx, inv), c in zip(held, counts, strict=True)]
            nodes = np.unique(np.concatenate([np.zeros(0, np.int64), *(ctx[t >= least] for (ctx, _), t in zip(held, totals, strict=True))]))
            shorter = nodes % size ** (d - 1)  # without its oldest symbol
            nodes = nodes[np.isin(shorter, codes[d - 1])]
        up = parent_rows[np.searchsorted(codes[d - 1], nodes % size ** (d - 1))] if d else base
        table = np.empty((len(nodes), size, len(languages)))
        for i, c in enumerate(counts):
            pair, n = c[d]
            ctx, sym = pair // size, pair % size
            at = np.searchsorted(nodes, ctx)
            ok = (at < len(nodes)) & (nodes[np.minimum(at, max(len(nodes) - 1, 0))] == ctx) if len(nodes) else np.zeros(len(ctx), bool)
            seen_n = np.zeros((len(nodes), size))
            seen_n[at[ok], sym[ok]] = n[ok]
            total, distinct = seen_n.sum(1, keepdims=True), (seen_n > 0).sum(1, keepdims=True)
            rest = np.where(seen_n > 0, 0.0, up[:, :, i])
            left = rest.sum(1, keepdims=True)
            escape = np.where(total + distinct > 0, distinct / np.maximum(total + distinct, 1), 1.0)
            table[:, :, i] = np.where(seen_n > 0, seen_n / np.maximum(total + distinct, 1), escape * rest / np.where(left > 0, left, 1.0))
            table[:, :, i] = np.where(total >= (least if d else 1), table[:, :, i], up[:, :, i])  # a context that another language keeps
        if d:
            view = deepest.reshape(-1, size**d)  # by the last d symbols
            view[:, nodes] = offset + np.arange(len(nodes), dtype=np.int32)
            codes.append(nodes)
        node_rows.append(table)
        offset += len(nodes)
        parent_rows = table
    p = np.concatenate(node_rows).reshape(-1, len(languages))
    others = max(256 - len(known), 1)
    p = p.reshape(-1, size, len(languages))
    p[:, -1, :] /= others  # one of the bytes that training lacks
    bits = -np.log2(np.maximum(p, 1e-30)).reshape(-1, len(languages)).astype(np.float32)
    return ContextTrees(languages, symbols.astype(np.int32), size, deepest, bits, order)


def code_lengths(model: ContextTrees, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Bits of each text in each language."""
    out = np.zeros((len(offsets) - 1, len(model.languages)))
    for a, b in slices(offsets):
        bounds = offsets[a : b + 1] - offsets[a]
        sym = model.symbols[data[offsets[a] : offsets[b]]]
        if not len(sym):
            continue
        full = np.flatnonzero(np.diff(bounds))
        starts = bounds[:-1][full]
        context = np.zeros(len(sym), np.int32)
        for d in range(1, model.order + 1):
            back = np.empty(len(sym), np.int32)
            back[d:] = sym[:-d] if d < len(sym) else sym[:0]
            for j in range(d):  # before a text lie line ends
                at = starts + j
                back[at[at < np.minimum(bounds[1:][full], len(sym))]] = model.symbols[10]
            context += back * np.int32(model.size ** (d - 1))
        cost = model.bits[model.deepest[context] * model.size + sym]
        out[a + full] = np.add.reduceat(cost, starts, axis=0, dtype=np.float64)
    return out


def sample(labelled: DataFrame, per_language: int = PER_LANGUAGE) -> dict[str, list[bytes]]:
    """Whole texts of at most per_language documents of each language of labelled (doc_id, text, lang), by hash of the id (ties: by id).

    The lowest hashes are found in two steps (first in each of SALTS parts of a language), of narrow rows; only the chosen texts are collected.
    """
    offered = labelled.where(F.col("doc_id").isNotNull() & (F.length("text") <= LONGEST))
    rows = offered.select("lang", "doc_id", F.xxhash64("doc_id", F.lit("sample")).alias("h"), F.pmod(F.xxhash64("doc_id", F.lit("salt")), F.lit(SALTS)).alias("salt")).distinct()
    for by in (["lang", "salt"], ["lang"]):
        rows = rows.withColumn("nth", F.row_number().over(Window.partitionBy(*by).orderBy("h", "doc_id"))).where(F.col("nth") <= per_language)
    some = offered.join(F.broadcast(rows.select("lang", "doc_id", "h")), ["lang", "doc_id"]).groupBy("lang", "h", "doc_id").agg(F.max(F.lower("text")).alias("text"))
    found: dict[str, list[tuple[int, int, bytes]]] = {}
    for r in some.collect():
        found.setdefault(r["lang"], []).append((r["h"], r["doc_id"], r["text"].encode()))
    return {x: [t for _, _, t in sorted(rows)] for x, rows in found.items()}


def _score(model: ContextTrees):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            bits = code_lengths(model, *text_buffers(batch.column(1)))
            best = bits.argmin(1)
            posterior = 1.0 / np.exp2(np.maximum(bits.min(1, keepdims=True) - bits, -1000)).sum(1)
            lettered = batch.column(2).to_numpy(zero_copy_only=False)
            names = [model.languages[i] if ok else "und" for i, ok in zip(best, lettered, strict=True)]
            n = pa.array(bits.min(1))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(3), pa.array(names, pa.string()), pa.array(np.where(lettered, posterior, 0.0)), n], ["doc_id", "held_out", "lang_pred", "score", "bits"])

    return run


def language_id(docs: DataFrame, model: ContextTrees | None, held_out: Column | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row of docs: doc_id, held_out, lang_pred, score, bits."""
    lettered = F.coalesce(column(text_col).rlike(r"\p{L}"), F.lit(False))
    held = F.lit(False) if held_out is None else held_out
    if model is None or not model.languages:
        return docs.select(column(id_col).cast("long").alias("doc_id"), held.alias("held_out"), F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"), F.lit(0.0).alias("bits"))
    given = docs.select(column(id_col).cast("long"), F.lower(column(text_col)), lettered, held)
    return given.mapInArrow(_score(model), "doc_id long, held_out boolean, lang_pred string, score double, bits double")


def learn_and_identify(docs: DataFrame, folds: int = 5, per_language: int = PER_LANGUAGE, order: int = ORDER) -> DataFrame:
    """Learn from rows outside the held-out fold that have a language and a text, then score all rows."""
    held = crc_mod(F.col("doc_id"), folds) == 0
    labelled = docs.where(~held & F.col("lang").isNotNull() & F.col("text").isNotNull()).select("doc_id", "text", "lang")
    texts = sample(labelled, per_language)
    return language_id(docs, train(texts, order) if texts else None, held)
