"""Best-fit packing by length patterns: non-negative least squares on the length histogram, then best fit for the rest.

Everything that decides is a function of the histogram of piece lengths, which has ``limit`` entries whatever the input.
Patterns that fill a sequence exactly get repeat counts by non-negative least squares; counts are rounded down, and what is
left is packed best fit, longest first, in groups of equal sequences.  The plan says for a run of pieces of one length
(numbered from 0) in which sequences and at which offsets they lie, so placing a piece is arithmetic on its number.
"""

from __future__ import annotations

import os
import zlib
from collections.abc import Iterator
from contextlib import contextmanager
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.llm import text as tx
from detspark.plans.scratch import staged

LIMIT = 4096
END = 1
_BUCKETS = 256
#: runs that are kept, at most, and the bytes of the longest; longer ones are tokenized anew
_YOUNG, _KEPT = 400_000, 64
#: bytes of ids in a batch that leaves a task, and rows in one that enters it
_OUT, _IN = 1 << 20, 256
_STOPS = b".,!?;:"


class WordCache(dict):
    """Token ids of white-space separated runs, as bytes, found on demand.

    The tokenizer drops white space and no match spans it, so the ids of a text are those of its runs in order.  It also
    lower-cases character by character and takes letters apart from punctuation, so a run is looked up in ASCII lower case,
    and stops after a letter or digit are looked up on their own.  Two generations of short runs, of ``young`` each, bound the
    memory, about 200 bytes a run.
    """

    def __init__(self, path: str, young: int = _YOUNG) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"  # tasks are the parallelism
        from tokenizers import Tokenizer

        super().__init__()
        self.tokenizer = Tokenizer.from_file(path)
        self.young = young
        self.old: dict[bytes, bytes] = {}

    def __missing__(self, run: bytes) -> bytes:
        found = self.old.get(run)
        if found is None:
            core = run.rstrip(_STOPS)
            if core and len(core) < len(run) and core.decode("utf-8", "replace")[-1].isalnum():
                found = self[core] + self[run[len(core) :]]
            else:
                coded = self.tokenizer.encode(run.decode("utf-8", "replace"), add_special_tokens=False)
                found = np.array(coded.ids, "<u4").tobytes()
        if len(run) <= _KEPT:
            self[run] = found
        return found

    def ids(self, text: bytes) -> bytes:
        if b"<|" not in text:  # names of special tokens count in lower case only
            text = text.lower()
        out = b"".join(map(self.__getitem__, text.split()))
        if len(self) > self.young:
            self.old.clear()
            self.old.update(self)
            self.clear()
        return out


@lru_cache(1)
def _cache(path: str, young: int) -> WordCache:
    return WordCache(path, young)


tx.HELD.append(_cache.cache_clear)


def pieces(docs: DataFrame, tokenizer: str, limit: int = LIMIT, with_ids: bool = False, young: int = _YOUNG) -> DataFrame:
    """``(doc_id, text)`` → ``doc_id, piece, start, length, ids_crc32`` [, ``ids``]; only documents over ``limit`` are cut.

    ``ids`` are little-endian unsigned 32-bit numbers, as training readers map them into memory.  Batches that leave are bounded in
    bytes, whatever comes in.  ``young`` bounds the runs that a worker remembers (twice so many at most) and not the result; a
    worker keeps them until it turns to another operator.

    A null or empty text is the end id alone; null and repeated ids are rows as any.  No shuffle.
    """
    fields = [T.StructField("doc_id", docs.schema["doc_id"].dataType), *(T.StructField(n, T.LongType()) for n in ("piece", "start", "length", "ids_crc32"))]
    schema = T.StructType([*fields, *([T.StructField("ids", T.BinaryType())] if with_ids else [])])
    end = np.array([END], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = _cache(tokenizer, young)
        tx.tidy()  # after the vocabulary is read, which leaves much behind
        for batch in batches:
            row, piece, start, length, crc, ids, size = [], [], [], [], [], [], 0

            def made(of: pa.Array = batch.column(0)) -> pa.RecordBatch:
                columns = [of.take(pa.array(row, pa.int64())), *(pa.array(x, pa.int64()) for x in (piece, start, length, crc))]  # noqa: B023
                return pa.RecordBatch.from_arrays([*columns, *([pa.array(ids, pa.binary())] if with_ids else [])], schema.names)  # noqa: B023

            for at, value in enumerate(batch.column(1).cast(pa.large_binary())):
                coded = cache.ids(value.as_buffer().to_pybytes() if value.is_valid else b"") + end
                for k, low in enumerate(range(0, len(coded), 4 * limit)):
                    part = coded[low : low + 4 * limit]
                    row.append(at)
                    piece.append(k)
                    start.append(low // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
                    if with_ids:
                        ids.append(part)
                        size += len(part)
                    if size >= _OUT:
                        yield made()
                        row, piece, start, length, crc, ids, size = [], [], [], [], [], [], 0
            yield made()

    return docs.select("doc_id", "text").mapInArrow(run, schema)


@contextmanager
def small_batches(spark: SparkSession, rows: int = _IN) -> Iterator[None]:
    """What runs inside hands its rows to Python in batches of ``rows`` at most; the session's own number comes back after it.

    A batch of texts is held by the executor and by its worker at once, so its size counts twice for each core.
    """
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, rows)
    try:
        yield
    finally:
        spark.conf.set(name, before)


def patterns(histogram: np.ndarray, limit: int, frequent: int = 96) -> list[tuple[int, ...]]:
    """Exactly filling patterns of one, two or three lengths that occur; in threes, two are among the most frequent."""
    there = histogram > 0
    found = {(limit,)} if there[limit] else set()
    lengths = np.flatnonzero(there[:limit])
    found |= {(int(a), int(limit - a)) for a in lengths if 2 * a <= limit and there[limit - a]}
    top = [int(x) for x in np.argsort(-histogram[:limit], kind="stable")[:frequent] if histogram[x] > 0]
    for i, a in enumerate(top):
        for b in top[i:]:
            c = limit - a - b
            if c > 0 and there[c]:
                found.add(tuple(sorted((a, b, c))))
    return sorted(found)


def nnls(rows: np.ndarray, columns: np.ndarray, goal: np.ndarray, n: int, steps: int = 400) -> np.ndarray:
    """Minimise |A x - goal|² over x >= 0, A having ones (added up) at (rows, columns): accelerated projected gradient."""
    if not n:
        return np.zeros(0)
    column_sum = np.bincount(columns, minlength=n)
    row_sum = np.bincount(rows, column_sum[columns], len(goal))
    bound = max(1.0, row_sum.max())  # of the largest eigenvalue of A'A
    x = y = np.zeros(n)
    t = 1.0
    for _ in range(steps):
        gap = np.bincount(rows, y[columns], len(goal)) - goal
        new = np.maximum(0.0, y - np.bincount(columns, gap[rows], n) / bound)
        later = (1 + np.sqrt(1 + 4 * t * t)) / 2
        y = new + (t - 1) / later * (new - x)
        x, t = new, later
    return x


def plan(histogram: np.ndarray, limit: int = LIMIT) -> tuple[pd.DataFrame, int]:
    """(runs, number of sequences) for counts by length 0..limit.

    A run ``(length, first, n, bin, each, offset)``: pieces first .. first+n-1 of this length lie ``each`` to a sequence,
    one behind the other from ``offset``, in sequences from ``bin`` on.
    """
    left = histogram.astype(np.int64).copy()
    rank = np.zeros(limit + 1, np.int64)
    runs: list[tuple[int, int, int, int, int, int]] = []
    bins = 0
    shapes = patterns(left, limit)
    rows = np.array([x for s in shapes for x in s], np.int64)
    columns = np.array([k for k, s in enumerate(shapes) for _ in s], np.int64)
    wanted = np.floor(nnls(rows, columns, left.astype(float), len(shapes)) + 1e-6).astype(np.int64)

    def put(length: int, n: int, at: int, each: int, offset: int) -> None:
        runs.append((length, int(rank[length]), n, at, each, offset))
        rank[length] += n
        left[length] -= n

    for k in np.argsort(-wanted, kind="stable").tolist():
        shape = shapes[k]
        kinds = {length: shape.count(length) for length in shape}
        times = min([int(wanted[k]), *(int(left[length]) // c for length, c in kinds.items())])
        if times <= 0:
            continue
        offset = 0
        for length, c in sorted(kinds.items(), reverse=True):
            put(length, times * c, bins, c, offset)
            offset += length * c
        bins += times
    # best fit, longest first: open sequences by the room they have
    room: list[list[tuple[int, int]]] = [[] for _ in range(limit + 1)]
    roomy = np.zeros(limit + 1, bool)
    for length in range(limit, 0, -1):
        while left[length] > 0:
            fitting = np.flatnonzero(roomy[length:])
            if len(fitting):
                space = length + int(fitting[0])
                at, count = room[space].pop()
                roomy[space] = bool(room[space])
            else:
                space, at = limit, bins
                count = -(-int(left[length]) // (limit // length))
                bins += count
            each = space // length
            full = min(count, int(left[length]) // each)
            if full:
                put(length, full * each, at, each, limit - space)
                room[space - each * length].append((at, full))
                roomy[space - each * length] = True
            if full < count and left[length] > 0:
                rest = int(left[length])
                put(length, rest, at + full, rest, limit - space)
                room[space - rest * length].append((at + full, 1))
                roomy[space - rest * length] = True
                full += 1
            if full < count:
                room[space].append((at + full, count - full))
                roomy[space] = True
    return pd.DataFrame(runs, columns=["_length", "first", "n", "bin", "each", "at"], dtype="int64"), bins


def pack(cut: DataFrame, limit: int = LIMIT) -> DataFrame:
    """Pieces (as from ``pieces``) with ``sequence_id`` and ``offset``.

    Pieces of a length are numbered inside hash buckets that are then offset, so a length with most of the pieces is dealt
    over many tasks.  The plan is broadcast: it has a few rows for each length up to ``limit``, not for each piece.  Pieces
    that agree in id, number and checksum may change places; an empty table stays empty.
    """
    spark = cut.sparkSession
    with small_batches(spark):
        cut = staged(cut, "pieces")
    placed = cut.withColumn("_b", F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32"), F.lit(_BUCKETS)).cast("int"))
    sizes = staged(placed.groupBy("length", "_b").agg(F.count("*").alias("_n")), "lengths")
    histogram = np.zeros(limit + 1, np.int64)
    for r in sizes.groupBy("length").agg(F.sum("_n").alias("n")).collect():  # at most `limit` rows
        histogram[r["length"]] = r["n"]
    runs, _ = plan(histogram, limit)
    before = F.sum("_n").over(Window.partitionBy("length").orderBy("_b").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sizes.select(F.col("length").alias("_l"), F.col("_b").alias("_k"), F.coalesce(before, F.lit(0)).alias("_o"))
    local = F.row_number().over(Window.partitionBy("length", "_b").orderBy("doc_id", "piece", "ids_crc32")) - 1
    ranked = placed.withColumn("_i", local).join(offsets, (F.col("length") == F.col("_l")) & (F.col("_b") == F.col("_k")))
    ranked = ranked.withColumn("_r", F.col("_o") + F.col("_i"))
    table = F.broadcast(spark.createDataFrame(runs, "_length long, first long, n long, bin long, each long, at long"))
    inside = (F.col("length") == F.col("_length")) & (F.col("_r") >= F.col("first")) & (F.col("_r") < F.col("first") + F.col("n"))
    step = F.col("_r") - F.col("first")
    return ranked.join(table, inside).select(
        *cut.columns,
        (F.col("bin") + F.floor(step / F.col("each"))).cast("long").alias("sequence_id"),
        (F.col("at") + step % F.col("each") * F.col("length")).cast("long").alias("offset"),
    )


def word_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def op7_packing(spark, sf_dir: str) -> DataFrame:
    """The token ids of every row of ``documents``, cut at 4096 and placed in sequences; null and empty texts are the end id alone, null
    and repeated ids are rows as any, an empty table gives no rows."""
    return pack(pieces(spark.read.parquet(f"{sf_dir}/documents.parquet"), word_tokenizer()))
