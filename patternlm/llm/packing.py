"""Bulk-synchronous best-fit packing of token pieces into sequences.

Pieces that are equally long are interchangeable, and so are equally wide gaps; a run is so many of one size. The runs of all unplaced pieces
(by length) and of all gaps (by width) are a table. A superstep, all of it Spark jobs on that table:

1. pieces and gaps are range-sorted by size, widest first, a gap before a piece of its size;
2. successor sweep: a piece takes the narrowest gap before it that no longer piece has taken. With running sums the gaps still free before
   each run are known, so a run covers an interval of levels (gaps push levels, pieces pop them), and a piece's successor at a level is the last
   push before it. Levels are cut into cells, which are swept independently; inside a cell a piece meets the run directly before it;
3. conflicts are resolved by rank: more pieces than free gaps leave the last ones unplaced, partial overlaps wait for the next superstep, and
   ranks and sequence numbers are handed out by running sums over the matched runs;
4. gaps are updated: a matched gap shrinks by its piece (and by more pieces of that length, if they found no gap of their own), and goes
   back into the order with its new width;
5. pieces that no gap is wide enough for open new sequences, longest first, as many as their tokens need at least.

Supersteps repeat until no piece is left (about ten, whatever the input). Runs are at most `capacity` lengths and a few thousand gaps, so a
superstep costs the same at any size; pieces themselves are shuffled once, to learn their rank within their length (two-level counting over
salts whose number grows with the length's count), and read sequence and offset from the table of matched runs.

Ids are those of the tokenizers library, added tokens included. A document is the ids of its text plus an end id. Longer than `capacity` it is
cut into full pieces after a shorter first one. Null and empty texts are just the end id. Repeated rows are packed each by itself; an empty
table gives an empty result.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from patternlm.llm.common import column
from patternlm.session import cut

CAPACITY = 1024
END_ID = 2
CELLS = 1 << 14  # at most so many cells of levels (and one more a run) are swept
LEAST_SALT = 512  # rows of a salt, at least
_ENCODERS: dict[str, object] = {}


def encoder(path: str):
    """text -> ids of the tokenizer file as the library gives them, without special tokens around the text.

    Beside a byte-level BPE file may lie the same vocabulary as ranks (`.tiktoken`), which encodes to the same ids several times faster.
    Texts that hold the string of an added token, and texts it refuses (its pattern engine has a stack limit), go to the tokenizer itself.
    """
    if path not in _ENCODERS:
        from pathlib import Path

        from tokenizers import Tokenizer

        slow = Tokenizer.from_file(path)
        by_file = lambda text: slow.encode(text, add_special_tokens=False).ids
        added = [t.content for t in slow.get_added_tokens_decoder().values()]
        ranks_file = Path(path).with_suffix(".tiktoken")
        if ranks_file.exists():
            import public_tokenizers
            import tiktoken

            ranks = {base64.b64decode(t): int(r) for t, r in map(bytes.split, ranks_file.read_bytes().splitlines())}
            fast = tiktoken.Encoding(ranks_file.stem, pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})

            def encode(text: str) -> list[int]:
                if any(t in text for t in added):
                    return by_file(text)
                try:
                    return fast.encode_ordinary(text)
                except BaseException as e:  # a panic of the native code is no Exception
                    if isinstance(e, (KeyboardInterrupt, SystemExit, MemoryError)):
                        raise
                    return by_file(text)

            _ENCODERS[path] = encode
        else:
            _ENCODERS[path] = by_file
    return _ENCODERS[path]


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def cuts(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n ids: full ones after a first that may be shorter."""
    first = n % capacity or capacity
    return [(0, min(n, first))] + [(s, capacity) for s in range(first, n, capacity)]


PIECE = "doc_id long, piece int, start long, length long, ids_crc32 long"


def _pieces(path: str | None, capacity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(path or default_tokenizer())
        for batch in batches:
            rows: list[tuple] = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = np.array([*encode(text.as_py() or ""), END_ID], "<u4")
                rows += [(doc_id, i, s, n, zlib.crc32(ids[s : s + n].tobytes())) for i, (s, n) in enumerate(cuts(len(ids), capacity))]
            columns = list(zip(*rows, strict=True)) or [()] * 5
            types = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def pieces(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    return docs.select(column(id_col).cast("long"), column(text_col).cast("string")).mapInArrow(_pieces(tokenizer, capacity), PIECE)


GAP, PIECES, OPENED = 0, 1, 2  # kinds of a run; an opened one is a record of new sequences


def _before(w):
    return w.rowsBetween(Window.unboundedPreceding, -1)


def _upto(w):
    return w.rowsBetween(Window.unboundedPreceding, 0)


def successors(runs: DataFrame, levels: int) -> DataFrame:
    """One sweep over runs (kind, size, first, n), `levels` of them gaps: pairs (length, first, rank, width, run, sequence, n, times).

    n sequences from `sequence` on, of the gap run (width, run), take `times` pieces each, of ranks from `rank` on, of the piece run (length, first).
    """
    order = Window.orderBy(F.desc("size"), "kind", "first")
    signed = F.when(F.col("kind") == GAP, F.col("n")).otherwise(-F.col("n"))
    e = runs.where(F.col("kind") != OPENED).select("kind", "size", "first", "n").coalesce(1)
    e = e.withColumn("at", F.row_number().over(order)).withColumn("sum", F.sum(signed).over(_upto(order)))
    e = e.withColumn("after", F.col("sum") - F.least(F.lit(0), F.min("sum").over(_upto(order))))
    e = e.withColumn("before", F.coalesce(F.lag("after").over(order), F.lit(0)))
    e = e.withColumn("lo", F.least("before", "after")).withColumn("hi", F.greatest("before", "after")).where("hi > lo")
    width = max(1, -(-levels // CELLS))
    cells = e.withColumn("cell", F.explode(F.sequence(F.expr(f"lo div {width}"), F.expr(f"(hi - 1) div {width}"))))
    cells = cells.withColumn("lo", F.greatest("lo", F.col("cell") * width)).withColumn("hi", F.least("hi", (F.col("cell") + 1) * width))
    last = F.lag(F.struct("kind", "size", "first", "lo", "hi")).over(Window.partitionBy("cell").orderBy("at"))
    met = cells.withColumn("gap", last).where((F.col("kind") == PIECES) & (F.col("gap.kind") == GAP))
    met = met.withColumn("both", F.least("hi", "gap.hi") - F.greatest("lo", "gap.lo")).where("both > 0")
    met = met.select(F.col("size").alias("length"), "first", F.col("n").alias("pieces"), F.col("gap.size").alias("width"), F.col("gap.first").alias("run"), "both")
    pairs = met.coalesce(1).groupBy("length", "first", "pieces", "width", "run").agg(F.sum("both").alias("n"))
    own, theirs = Window.partitionBy("length").orderBy("width", "run"), Window.partitionBy("width", "run").orderBy(F.desc("length"))
    more = F.expr("width div length") - 1  # pieces of this length that the gap could take besides
    spare = F.col("pieces") - F.sum("n").over(Window.partitionBy("length"))
    pairs = pairs.withColumn("times", 1 + F.when(F.sum(F.col("n") * more).over(_upto(own)) <= spare, more).otherwise(0))
    rank = F.col("first") + F.coalesce(F.sum(F.col("n") * F.col("times")).over(_before(own)), F.lit(0))
    sequence = F.col("run") + F.coalesce(F.sum("n").over(_before(theirs)), F.lit(0))
    return pairs.select("length", "first", rank.alias("rank"), "width", "run", sequence.alias("sequence"), "n", "times")


def updated(runs: DataFrame, pairs: DataFrame) -> DataFrame:
    """The runs after a sweep: what it left of them, and the matched gaps with their new widths."""
    one, key = pairs.coalesce(1), ["kind", "size", "first"]
    gaps = one.groupBy(F.lit(GAP).alias("kind"), F.col("width").alias("size"), F.col("run").alias("first")).agg(F.sum("n").alias("used"))
    pieces_ = one.groupBy(F.lit(PIECES).alias("kind"), F.col("length").alias("size"), "first").agg(F.sum(F.col("n") * F.col("times")).alias("used"))
    left = runs.where(F.col("kind") != OPENED).coalesce(1).join(F.broadcast(gaps.unionByName(pieces_)), key, "left").withColumn("used", F.coalesce("used", F.lit(0)))
    left = left.select("kind", "size", (F.col("first") + F.col("used")).alias("first"), (F.col("n") - F.col("used")).alias("n"))
    shrunk = one.select(F.lit(GAP).alias("kind"), (F.col("width") - F.col("length") * F.col("times")).alias("size"), F.col("sequence").alias("first"), "n")
    return left.unionByName(shrunk).where("n > 0 AND size > 0")


def opened(runs: DataFrame, base: int, capacity: int) -> DataFrame:
    """runs after new sequences, numbered from base, were opened: (kind, size, first, n, times, sequence), the records of them included.

    All pieces longer than half the capacity that no gap holds open one each. Of the shorter ones as many sequences are opened, longest pieces first,
    as the tokens need that exceed all gaps, or those that no gap holds.
    """
    every, order = Window.partitionBy(), Window.orderBy(F.desc("size"), "first")
    piece, tokens, room = F.col("kind") == PIECES, F.col("size") * F.col("n"), capacity - F.col("size")
    r = runs.coalesce(1).withColumn("widest", F.coalesce(F.max(F.when(~piece, F.col("size"))).over(every), F.lit(0)))
    r = r.withColumn("big", piece & (F.col("size") > F.col("widest")) & (2 * F.col("size") > capacity))
    r = r.withColumn("widest", F.greatest("widest", F.coalesce(F.max(F.when(F.col("big"), room)).over(every), F.lit(0))))
    r = r.withColumn("stuck", piece & ~F.col("big") & (F.col("size") > F.col("widest")))
    free = F.sum(F.when(~piece, tokens).when(F.col("big"), F.col("n") * room).otherwise(-tokens)).over(every)
    r = r.withColumn("need", F.greatest(F.ceil(-free / capacity), F.ceil(F.sum(F.when(F.col("stuck"), tokens).otherwise(0)).over(every) / capacity)))
    each = F.least(F.col("n"), F.when(F.col("big"), F.lit(1)).otherwise(F.expr(f"{capacity} div size")))
    r = r.withColumn("times", F.when(F.col("big") | F.col("stuck"), each).otherwise(0)).withColumn("could", F.when(F.col("times") > 0, F.expr("n div times")).otherwise(0))
    asked = F.coalesce(F.sum(F.when(F.col("stuck"), F.col("could")).otherwise(0)).over(_before(order)), F.lit(0))
    r = r.withColumn("opens", F.when(F.col("big"), F.col("n")).when(F.col("stuck"), F.greatest(F.lit(0), F.least(F.col("could"), F.col("need") - asked))).otherwise(0))
    r = r.withColumn("sequence", base + F.coalesce(F.sum("opens").over(_before(order)), F.lit(0)))
    used, none = F.col("opens") * F.col("times"), F.lit(None).cast("long")

    def run(kind, size, first, n, times=none, sequence=none):
        return F.struct(kind.cast("int").alias("kind"), size.cast("long").alias("size"), first.cast("long").alias("first"), n.cast("long").alias("n"), times.cast("long").alias("times"), sequence.cast("long").alias("sequence"))

    rows = F.array(
        run(F.col("kind"), F.col("size"), F.col("first") + used, F.col("n") - used),
        run(F.lit(GAP), capacity - F.col("size") * F.col("times"), F.col("sequence"), F.col("opens")),
        run(F.lit(OPENED), F.col("size"), F.col("first"), F.col("opens"), F.col("times"), F.col("sequence")),
    )
    return r.select(F.inline(F.filter(rows, lambda x: (x["n"] > 0) & (x["size"] > 0))))


def best_fit(counts: DataFrame, capacity: int) -> np.ndarray:
    """Matched runs (length, first rank, ranks, first sequence, offset) of a best-fit packing of counts (length, n)."""
    start = counts.select(F.lit(PIECES).alias("kind"), F.col("length").cast("long").alias("size"), F.lit(0).cast("long").alias("first"), F.col("n").cast("long").alias("n"))
    runs, told, step = cut(opened(start, 0, capacity), "pack-runs"), [], 0
    record = lambda df, *c: df.select(*(x.cast("long") for x in c))
    while True:
        told.append(record(runs.where(F.col("kind") == OPENED), F.col("size"), F.col("first"), F.col("n"), F.col("times"), F.col("sequence"), F.lit(0)))
        left = runs.where(F.col("kind") != OPENED).groupBy("kind").agg(F.sum("n").alias("n")).collect()  # two numbers
        left = {r["kind"]: r["n"] for r in left}
        if not left.get(PIECES):
            break
        step += 1
        pairs = cut(successors(runs, left.get(GAP, 0)), "pack-pairs")
        told.append(record(pairs, F.col("length"), F.col("rank"), F.col("n"), F.col("times"), F.col("sequence"), capacity - F.col("width")))
        runs = cut(opened(updated(runs, pairs), step << 40, capacity), "pack-runs")
    rows = np.array([tuple(r) for df in told for r in df.collect()], np.int64).reshape(-1, 6)  # matched runs: some thousands, whatever the input
    ends = np.cumsum(rows[:, 3])
    copy = np.arange(ends[-1] if len(rows) else 0) - np.repeat(ends - rows[:, 3], rows[:, 3])
    rows = np.repeat(rows, rows[:, 3], axis=0)
    return np.stack([rows[:, 0], rows[:, 1] + copy * rows[:, 2], rows[:, 2], rows[:, 4], rows[:, 5] + copy * rows[:, 0]], 1)


def _placed(runs: np.ndarray):
    order = np.lexsort((runs[:, 1], runs[:, 0]))
    table = runs[order]
    first = {int(x): int(i) for x, i in zip(*np.unique(table[:, 0], return_index=True), strict=True)}
    upto = {int(x): first[int(x)] + int(c) for x, c in zip(*np.unique(table[:, 0], return_counts=True), strict=True)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            row = np.empty(len(length), np.int64)
            for x in np.unique(length):
                a, b, own = first[int(x)], upto[int(x)], length == x
                row[own] = a + np.searchsorted(table[a:b, 1], rank[own], side="right") - 1
            sequence = table[row, 3] + rank - table[row, 1]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(5)), pa.array(sequence), pa.array(table[row, 4])], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return run


def pack(cut_pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Pieces with sequence_id and offset. cut_pieces must be a table (it is read more than once) with a number `turn` in each row."""
    lengths = cut(cut_pieces.groupBy("length").agg(F.count("*").alias("n")), "pack-lengths")  # at most `capacity` rows
    salts = F.ceil(F.col("n") / F.greatest(F.lit(LEAST_SALT), F.sqrt("n"))).cast("long")
    salted = cut_pieces.join(F.broadcast(lengths.select("length", salts.alias("salts"))), "length").withColumn("salt", F.pmod(F.xxhash64("turn"), F.col("salts")))
    held = salted.groupBy("length", "salt").agg(F.count("*").alias("n"))
    base = held.select("length", "salt", F.coalesce(F.sum("n").over(_before(Window.partitionBy("length").orderBy("salt"))), F.lit(0)).alias("base"))
    ranked = salted.withColumn("nth", F.row_number().over(Window.partitionBy("length", "salt").orderBy("turn"))).join(base, ["length", "salt"])
    ranked = ranked.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("nth") - 1).alias("rank"))
    return ranked.mapInArrow(_placed(best_fit(lengths, capacity)), PIECE + ", sequence_id long, offset long")


def best_fit_packing(docs: DataFrame, capacity: int = CAPACITY, **options) -> DataFrame:
    """Every piece of every row of docs: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    return pack(cut(pieces(docs, capacity=capacity, **options).withColumn("turn", F.monotonically_increasing_id()), "pack-pieces"), capacity)
