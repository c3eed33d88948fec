"""SimHash near-duplicates by anchor-point covering.

Fingerprints have 64 bits and link at ``THRESHOLD`` = 4 or fewer differing bits.  The bits are cut into three segments of
22, 22 and 20.  Two fingerprints within 4 bits differ by at most one bit in one of the first two segments or not at all in
the third (otherwise they would differ in 2 + 2 + 1 bits).  Each segment has a covering code as its anchors:

* 22 bits, segment threshold 1: a perfect single-error code on 15 bits times all words of the other 7; covering radius 1.
* 20 bits, segment threshold 0: all words; covering radius 0.

A fingerprint is *at home* at the one anchor within the covering radius and *visits* every anchor within covering radius
plus segment threshold (16 on average for the first kind, 1 for the second).  If two segments are within the threshold, the
home of the one is visited by the other, so homes against visitors at each anchor finds every link.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.llm import text as tx
from detspark.llm.graph import components, forest
from detspark.plans.scratch import staged

THRESHOLD = 4
WORDS = 4
_TABLE = tx.LOWER.tobytes()
_PAIRS = 1 << 21


def fingerprint(text: bytes | None, words: int = WORDS) -> int:
    """Bit k is set if it is set in over half of the shingle hashes, repeats included; no words give zero.

    Shingles are hashed in slices, so memory follows the text and not its number of bits.
    """
    parts = (text or b"").translate(_TABLE).split()
    if not parts:
        return 0
    joined = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    k = min(words, len(parts))
    digest, n = xxhash.xxh64_intdigest, len(parts) - k + 1
    counts = np.zeros(64, np.int64)
    for at in range(0, n, 1 << 15):
        top = min(n, at + (1 << 15))
        first, last = starts[at:top].tolist(), ends[at + k - 1 : top + k - 1].tolist()
        h = np.array([digest(joined[a:b], 42) for a, b in zip(first, last, strict=True)], np.uint64)
        bits = np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int64)
    return int(sum(1 << i for i in np.flatnonzero(2 * counts > n).tolist()))


def with_fingerprint(docs: DataFrame, text: str = "text", out: str = "fp", words: int = WORDS) -> DataFrame:
    """``docs`` without its text and with the fingerprint as a long (two's complement); no shuffle."""
    kept = [f for f in docs.schema.fields if f.name not in (text, out)]
    names = [f.name for f in kept]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        for batch in batches:
            column = batch.column(batch.schema.get_field_index(text)).cast(pa.large_binary())
            found = np.array([fingerprint(x.as_buffer().to_pybytes() if x.is_valid else None, words) for x in column], np.uint64)
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(n)) for n in names), pa.array(found.view(np.int64))], [*names, out])

    return docs.mapInArrow(run, T.StructType([*kept, T.StructField(out, T.LongType())]))


def _parity_columns() -> np.ndarray:
    """Syndrome of each single bit of the 15-bit code: the bit's position, from 1."""
    return np.arange(1, 16, dtype=np.int64)


def _syndrome(word: np.ndarray) -> np.ndarray:
    """Exclusive or of the positions of the set bits; zero for code words, else the position to flip."""
    out = np.zeros(len(word), np.int64)
    for bit, column in enumerate(_parity_columns().tolist()):
        out ^= ((word >> bit) & 1) * column
    return out


def _moves() -> list[list[int]]:
    """For each syndrome, every change of up to two bits of a 22-bit word that leads to an anchor."""
    out: list[list[int]] = [[] for _ in range(16)]
    for size in range(3):
        for bits in combinations(range(22), size):
            syndrome = 0
            for b in bits:
                syndrome ^= b + 1 if b < 15 else 0
            out[syndrome].append(sum(1 << b for b in bits))
    return out


_MOVES = [np.array(m, np.int64) for m in _moves()]


def anchors(fp: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, anchor key, home?) of every anchor that each fingerprint lives at or visits; the segment is part of the key."""
    rows, keys, homes = [], [], []
    everyone = np.arange(len(fp))
    unsigned = fp.view(np.uint64)
    for segment, shift in ((0, 0), (1, 22)):
        word = ((unsigned >> np.uint64(shift)) & np.uint64((1 << 22) - 1)).astype(np.int64)
        syndrome = _syndrome(word & 0x7FFF)
        home = word ^ np.where(syndrome > 0, np.int64(1) << np.maximum(syndrome - 1, 0), 0)
        rows.append(everyone)
        keys.append(home | (segment << 24))
        homes.append(np.ones(len(fp), bool))
        for s in range(16):
            who = np.flatnonzero(syndrome == s)
            if len(who):
                rows.append(np.repeat(who, len(_MOVES[s])))
                keys.append(((word[who][:, None] ^ _MOVES[s][None, :]) | (segment << 24)).ravel())
                homes.append(np.zeros(len(who) * len(_MOVES[s]), bool))
    last = (unsigned >> np.uint64(44)).astype(np.int64) | (2 << 24)
    for home in (True, False):
        rows.append(everyone)
        keys.append(last)
        homes.append(np.full(len(fp), home))
    return np.concatenate(rows), np.concatenate(keys), np.concatenate(homes)


def _replicate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    tx.release()
    for batch in batches:
        fp = batch.column(0).to_numpy()
        for at in range(0, len(fp), 1 << 14):
            part = fp[at : at + (1 << 14)]
            row, key, home = anchors(part)
            yield pa.RecordBatch.from_arrays([pa.array(key * 2 + ~home), pa.array(part[row])], ["place", "fp"])


def _pairs(homes: np.ndarray, home_at: np.ndarray, home_n: np.ndarray, visitors: np.ndarray, at: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Links between each visitor and the homes of its anchor, in slices of bounded size."""
    n = home_n[at]
    live = n > 0
    visitors, first, n = visitors[live], home_at[at][live], n[live]
    total = np.cumsum(n)
    low = 0
    while low < len(visitors):
        done = total[low - 1] if low else 0
        high = max(low + 1, int(np.searchsorted(total, done + _PAIRS, side="right")))
        for cut in range(0, int(n[low]) if high == low + 1 else 1, _PAIRS):  # a single visitor of a very full anchor
            take = np.minimum(n[low:high] - cut, _PAIRS) if high == low + 1 else n[low:high]
            v = np.repeat(visitors[low:high], take)
            offset = np.arange(len(v)) - np.repeat(np.cumsum(take) - take, take) + cut
            h = homes[np.repeat(first[low:high], take) + offset]
            near = (h < v) & (np.bitwise_count((h ^ v).view(np.uint64)) <= THRESHOLD)
            yield h[near], v[near]
        low = high


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by place (anchor, homes before visitors): a spanning forest of the task's links.

    The homes of the anchor at hand stay in memory, visitors are taken batch by batch.
    """
    tx.release()
    carried_key, carried = None, np.zeros(0, np.int64)
    left: list[np.ndarray] = []
    right: list[np.ndarray] = []
    size = 0
    for batch in batches:
        place, fp = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        key, visitor = place >> 1, (place & 1).astype(bool)
        home_key, homes = key[~visitor], fp[~visitor]
        if carried_key is not None:
            home_key, homes = np.concatenate([np.full(len(carried), carried_key), home_key]), np.concatenate([carried, homes])
        keys, home_at, home_n = np.unique(home_key, return_index=True, return_counts=True)
        if len(keys):
            at = np.searchsorted(keys, key[visitor])
            known = (at < len(keys)) & (keys[np.minimum(at, len(keys) - 1)] == key[visitor])
            for a, b in _pairs(homes, home_at, home_n, fp[visitor][known], at[known]):
                left.append(a)
                right.append(b)
                size += len(a)
                if size > 1 << 20:
                    x, y = forest(np.concatenate(left), np.concatenate(right))
                    left, right, size = [x], [y], len(x)
        if len(key):
            now = key[-1]
            carried_key, carried = now, homes[home_key == now]
    x, y = forest(np.concatenate(left), np.concatenate(right)) if left else (np.zeros(0, np.int64),) * 2
    yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["u", "v"])


def near_links(fingerprints: DataFrame) -> DataFrame:
    """Distinct fingerprints ``(fp)`` → links ``(u, v)`` whose components are those of all pairs within the threshold.

    Copies of a fingerprint count once.  Full anchors are bounded by the number of distinct fingerprints that share 22 bits
    nearly; only links of a spanning forest leave a task, so a large group of near copies gives as many rows as members.
    """
    spark = fingerprints.sparkSession
    distinct = fingerprints.select("fp").distinct()
    placed = distinct.mapInArrow(_replicate, "place long, fp long")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = placed.repartition(parts, F.shiftright("place", 1)).sortWithinPartitions("place")
    return dealt.mapInArrow(_compare, "u long, v long")


def _grouped(docs: DataFrame, words: int) -> tuple[DataFrame, DataFrame]:
    """(rows, classes) of ``docs(doc_id, text, …)``: rows without their text and with ``fp``, staged; for each fingerprint its smallest
    id and ``c``, the smallest fingerprint of its group."""
    marked = staged(with_fingerprint(docs, words=words), "fingerprints")
    ids = staged(marked.groupBy("fp").agg(F.min("doc_id").alias("low")), "classes")
    labels = components(near_links(ids)).select(F.col("node").alias("fp"), F.col("component").alias("c"))
    return marked, ids.join(labels, "fp", "left").select("fp", "low", F.coalesce("c", "fp").alias("c"))


def groups(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """Documents ``(doc_id, text)`` → ``(doc_id, fp, component_id)``, one row per row.

    component_id is the smallest doc_id reachable by links, itself included.  Texts without words (null or empty too) have
    fingerprint zero and link like any other.  A null doc_id keeps its fingerprint; it is ignored as a smallest id unless
    its group has no other.  Repeated rows each come out.
    """
    marked, classed = _grouped(docs.select("doc_id", "text"), words)
    lows = classed.groupBy("c").agg(F.min("low").alias("component_id"))
    return marked.join(classed.join(lows, "c").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def keep_one(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """One row of each near-duplicate group, all columns unchanged: of the smallest doc_id, null last, the first by a hash of the row.

    Groups are those of texts, so rows that repeat an id, or have none, are each kept if no other row of their group is.
    Texts without words (null or empty too) are one group.  Rows are named by two hashes of all columns; rows equal in all of
    them are one.  Columns may have any name.  An empty table stays empty.
    """
    there = [F.col(f"`{c}`") for c in docs.columns]
    nulls = [c.isNull() for c in there]
    h1, h2 = F.xxhash64(*there, *nulls), F.xxhash64(F.lit(1), *nulls, *there)
    marked, classed = _grouped(docs.select("doc_id", "text", h1.alias("h1"), h2.alias("h2")), words)
    order = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "h1", "h2")
    first = marked.join(classed.select("fp", "c"), "fp").groupBy("c").agg(F.min(order).alias("first"))
    used = "doc_id", "text"
    named = docs.select(*[F.col(c) for c in used], h1.alias("h1"), h2.alias("h2"), tx.carried_rest(docs, used))
    kept = named.join(first.select("first.h1", "first.h2"), ["h1", "h2"], "left_semi")
    return kept.dropDuplicates(["h1", "h2"]).select(*tx.unpacked(docs, {}, used))


def op10_simhash(spark, sf_dir: str) -> DataFrame:
    """Every row of ``documents`` with the fingerprint of its whole text and the smallest doc_id that links of 4 or fewer bits reach.

    Null, empty and wordless texts have fingerprint zero; repeated rows come out each; a null doc_id is never the smallest
    while its group has another; an empty table gives no rows.
    """
    found = groups(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")
