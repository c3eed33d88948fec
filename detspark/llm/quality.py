"""Quality classifier: hashed word n-gram logistic regression, trained with follow-the-regularised-leader updates."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.llm import text as tx


@dataclass(frozen=True)
class QualityConfig:
    """``sample_rows`` bounds the labelled rows that train (expected number, chosen by a hash of doc_id)."""

    bits: int = 18
    sample_rows: int = 12_000
    epochs: int = 3
    alpha: float = 0.15
    beta: float = 1.0
    l1: float = 0.02
    l2: float = 1.0
    threshold: float = 0.3


_SEPARATORS = (tx.CLASSES == 0).astype(np.uint8)
#: the pair of a word with itself is one feature, whatever the word
_TWICE = np.uint64(0x5DEECE66D)


def _grams(column: pa.Array, bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, bucket) of every word and every pair of neighbouring words, chunk by chunk, over whole texts."""
    offsets, data = tx.column_bytes(column)
    mask, last_row, last_hash = np.uint64((1 << bits) - 1), -1, None
    for rows, bounds, chunk in tx.pieces(offsets, data, _SEPARATORS):
        starts, ends = tx.spans(chunk, tx.CLASSES, bounds)
        if not len(starts):
            continue
        hashes = tx.hash_spans(chunk, starts, ends)
        row = rows[np.searchsorted(bounds, starts, side="right") - 1]
        if last_row == row[0]:  # a long text goes on: its last word still pairs with the next
            before, before_row = np.concatenate([[last_hash], hashes[:-1]]), np.concatenate([[last_row], row[:-1]])
        else:
            before, before_row = np.concatenate([[np.uint64(0)], hashes[:-1]]), np.concatenate([[-1], row[:-1]])
        last_row, last_hash = row[-1], hashes[-1]
        paired = before_row == row
        with np.errstate(over="ignore"):
            pairs = tx.mix(before[paired] * np.uint64(3) + hashes[paired])
        pairs[before[paired] == hashes[paired]] = _TWICE
        yield np.concatenate([row, row[paired]]), (np.concatenate([hashes, pairs]) & mask).astype(np.int64)


def _features(column: pa.Array, bits: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Distinct buckets and values of each text: occurrences over the root of their number."""
    found: list[list[np.ndarray]] = [[] for _ in range(len(column))]
    for row, bucket in _grams(column, bits):
        order = np.argsort(row, kind="stable")
        row, bucket = row[order], bucket[order]
        cuts = np.flatnonzero(np.diff(row)) + 1
        for r, part in zip(row[np.concatenate([[0], cuts])], np.split(bucket, cuts), strict=True):
            found[r].append(part)
    out = []
    for parts in found:
        bucket, n = np.unique(np.concatenate(parts) if parts else np.zeros(0, np.int64), return_counts=True)
        out.append((bucket.astype(np.int32), (n / np.sqrt(max(1, n.sum()))).astype(np.float32)))
    return out


def ftrl(examples: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, cfg: QualityConfig) -> np.ndarray:
    """Weights after ``epochs`` passes in the given order; the last slot is the bias."""
    size = (1 << cfg.bits) + 1
    z, n = np.zeros(size), np.zeros(size)

    def weights(zi: np.ndarray, ni: np.ndarray) -> np.ndarray:
        return np.where(np.abs(zi) <= cfg.l1, 0.0, -(zi - np.sign(zi) * cfg.l1) / ((cfg.beta + np.sqrt(ni)) / cfg.alpha + cfg.l2))

    for _ in range(cfg.epochs):
        for (bucket, value), y in zip(examples, labels, strict=True):
            at, x = np.append(bucket, size - 1), np.append(value, 1.0)
            zi, ni = z[at], n[at]
            w = weights(zi, ni)
            p = 1.0 / (1.0 + np.exp(-np.clip(w @ x, -35, 35)))
            g = (p - y) * x
            grown = ni + g * g
            z[at] = zi + g - (np.sqrt(grown) - np.sqrt(ni)) / cfg.alpha * w
            n[at] = grown
    return weights(z, n)


def train(docs: DataFrame, labels: DataFrame, cfg: QualityConfig = QualityConfig()) -> np.ndarray:
    """Fit on at most about ``sample_rows`` labelled texts, in one task of bounded size, and return the weights.

    Rows without id, label or text do not train.  Equal rows of an id and text train once, with the larger of their labels;
    rows that share an id but not a text each train.  With no rows the weights are zero and every score is 0.5.
    """
    marked = labels.select(F.col("doc_id").alias("_id"), F.col("quality").alias("_y")).where("_id is not null and _y in (0, 1)")
    total = marked.count()
    share = min(1.0, cfg.sample_rows / max(1, total))
    marked = marked.where((F.pmod(F.xxhash64("_id", F.lit("quality")), F.lit(1 << 30)) < int(share * (1 << 30))))
    rows = docs.select(F.col("doc_id").alias("_id"), F.col("text").alias("_text")).where("_text is not null").join(marked, "_id")
    rows = rows.groupBy("_id", "_text").agg(F.max("_y").alias("_y")).withColumn("_one", F.lit(0))

    def fit(frame: pd.DataFrame) -> pd.DataFrame:
        tx.release()
        order = frame["_id"].map(lambda x: (x * 0x9E3779B97F4A7C15 + 11) % (1 << 64))
        frame = frame.assign(_o=order).sort_values(["_o", "_text"], kind="stable")
        examples, texts = [], frame.pop("_text")
        for at in range(0, len(texts), 256):  # whole texts, few at a time
            examples += _features(pa.array(texts.iloc[at : at + 256], pa.string()), cfg.bits)
        w = ftrl(examples, frame["_y"].to_numpy(), cfg)
        return pd.DataFrame({"weights": [w.astype(np.float32).tobytes()]})

    found = rows.groupBy("_one").applyInPandas(fit, "weights binary").first()
    return np.frombuffer(found["weights"], np.float32) if found else np.zeros((1 << cfg.bits) + 1, np.float32)


def _scores(column: pa.Array, weights: np.ndarray, bits: int) -> np.ndarray:
    total, count = np.zeros(len(column)), np.zeros(len(column))
    for row, bucket in _grams(column, bits):
        total += np.bincount(row, weights[bucket], len(column))
        count += np.bincount(row, minlength=len(column))
    return 1.0 / (1.0 + np.exp(-np.clip(total / np.sqrt(np.maximum(count, 1)) + weights[-1], -35, 35)))


def score(docs: DataFrame, weights: np.ndarray, text: str = "text", out: str = "score", cfg: QualityConfig = QualityConfig()) -> DataFrame:
    """``docs`` with a column ``out`` in 0..1 (an existing column of that name is replaced); no shuffle.

    Null and empty texts get the bias alone.
    """
    docs = docs.drop(out)
    schema = T.StructType([*docs.schema.fields, T.StructField(out, T.DoubleType())])
    held = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        for batch in batches:
            got = _scores(batch.column(batch.schema.get_field_index(text)), held.value, cfg.bits)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(got)], [*batch.schema.names, out])

    return docs.mapInArrow(run, schema)


def accept(docs: DataFrame, weights: np.ndarray, cfg: QualityConfig = QualityConfig()) -> DataFrame:
    """Rows of ``docs`` whose score reaches the threshold, all columns unchanged; no shuffle."""
    held = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tx.release()
        for batch in batches:
            got = _scores(batch.column(batch.schema.get_field_index("text")), held.value, cfg.bits)
            yield batch.filter(pa.array(got >= cfg.threshold))

    return docs.mapInArrow(run, docs.schema)


def held_out(doc_id: str = "doc_id") -> F.Column:
    """True for the fold that never trains; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def op1_quality(spark, sf_dir: str) -> DataFrame:
    """Every row of ``documents`` with its fold, score and prediction; null and empty texts get the bias alone, rows with null or
    repeated ids are scored as any, an empty table gives no rows."""
    cfg = QualityConfig()
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    weights = train(docs.where(~held_out()), labels.where(~held_out()), cfg)
    scored = score(docs, weights, cfg=cfg)
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= cfg.threshold).cast("int").alias("predicted"))
