"""Duplicate removal by sample-chosen key ranges: local sort and regular sample, splitters, one exchange, local compaction."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.functions.schema import require
from detspark.plans.scratch import staged

#: most samples per partition, and most samples that are merged on the driver at once
SAMPLES = 1000
DRIVER_SAMPLES = 1_000_000


@dataclass(frozen=True)
class DedupReport:
    """Cost of one run: rows in, rows left by local removal, rows exchanged, unique rows, samples, duplicates at borders, and the counts per part."""

    generated: int
    locally_removed: int
    exchanged: int
    unique: int
    samples: int
    boundary_duplicates: int
    parts: DataFrame


def key_names(frame: DataFrame) -> list[str]:
    """Word columns, lowest first."""
    names = sorted((c for c in frame.columns if c[0] == "w" and c[1:].isdigit()), key=lambda c: int(c[1:]))
    if not names:
        raise ValueError(f"no word columns among {frame.columns}")
    return names


def _matrix(batch: pa.RecordBatch) -> np.ndarray:
    return np.stack([c.to_numpy() for c in batch.columns], 1) if batch.num_rows else np.zeros((0, batch.num_columns), np.int64)


def _batch(words: np.ndarray, names: list[str]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(words[:, k])) for k in range(len(names))], names)


def unique_rows(words: np.ndarray) -> np.ndarray:
    """Distinct rows in key order (highest word first)."""
    if words.shape[1] == 1:
        return np.unique(words[:, 0])[:, None]
    words = words[np.lexsort(words.T)]
    keep = np.concatenate([[True], (words[1:] != words[:-1]).any(1)]) if len(words) else np.zeros(0, bool)
    return words[keep]


def _once(laid: DataFrame, names: list[str]) -> DataFrame:
    """Rows in key order, of which copies lie side by side in a task, without the copies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            rows = _matrix(batch)
            if len(rows):
                keep = np.concatenate([[last is None or (rows[0] != last).any()], (rows[1:] != rows[:-1]).any(1)])
                last = rows[-1]
                yield _batch(rows[keep], names)

    return laid.mapInArrow(run, laid.schema)


def local(frame: DataFrame) -> DataFrame:
    """Distinct keys within each task, in key order, whatever their number; no shuffle.  What repeats across tasks stays.

    Spark's sort, which goes to disk where it must, brings the copies together.
    """
    names = key_names(frame)
    return _once(frame.select(*names).sortWithinPartitions(*names[::-1]), names)


def sorted_runs(frame: DataFrame, distinct: bool = False) -> DataFrame:
    """Keys written in key order within each task, so that every file is a sorted run; sampling and routing read them back.

    ``distinct``: a task's copies of a key, which then lie side by side, are removed on the way, whatever their number.
    """
    names = key_names(frame)
    laid = frame.select(*names).sortWithinPartitions(*names[::-1])
    return staged(_once(laid, names) if distinct else laid, "runs")


def sample_runs(runs: DataFrame, s: int) -> DataFrame:
    """From each sorted run of D keys those at places ``floor(k D / s)``, k = 0..s-1 (all if D < s): ``words, weight, pid``.

    ``weight``: keys that a sample stands for; ``pid`` names the run.  A key's place is its row number in the file, so nothing
    is sorted or held again, and the sample is the same however the files are split for reading.  All of it runs in the JVM.
    """
    names = key_names(runs)
    rows = runs.select(*names, F.xxhash64("_metadata.file_path").alias("_f"), F.col("_metadata.row_index").alias("_r"))
    sizes = rows.groupBy("_f").agg(F.count("*").alias("_d"))
    k = F.ceil(F.col("_r") * s / F.col("_d"))  # the first k whose place is not before this row
    chosen = (F.col("_d") < s) | ((k < s) & (F.floor(k * F.col("_d") / s) == F.col("_r")))
    weight = F.col("_d") / F.least(F.col("_d"), F.lit(s))
    # a row for each task that wrote a run
    return rows.join(F.broadcast(sizes), "_f").where(chosen).select(*names, weight.alias("weight"), F.pmod("_f", F.lit(1 << 30)).cast("int").alias("pid"))


def regular_sample(frame: DataFrame, s: int) -> DataFrame:
    """``sample_runs`` of the sorted runs of each task of ``frame``."""
    return sample_runs(sorted_runs(frame), s)


def _cut(words: np.ndarray, weight: np.ndarray, parts: int) -> np.ndarray:
    """Splitter j: the first sample at which the weight so far reaches j / parts of the total."""
    if not len(words) or parts < 2:
        return np.zeros((0, words.shape[1]), np.int64)
    order = np.lexsort(words.T)
    words, total = words[order], np.cumsum(weight[order])
    goal = np.arange(1, parts) / parts * total[-1]
    return words[np.minimum(np.searchsorted(total, goal, side="left"), len(words) - 1)]


def splitters(samples: DataFrame, parts: int, levels: int = 1) -> np.ndarray:
    """``parts - 1`` cut keys from weighted samples.

    One level sorts all samples on the driver.  Two levels first thin the samples in groups of tasks: each group sorts its
    own and passes on every root-of-``parts``-th, so the driver gets a root of the number.  More than ``DRIVER_SAMPLES``
    are always thinned first.
    """
    names = key_names(samples)
    stats = samples.agg(F.count("*"), F.countDistinct("pid")).first()
    if levels == 2 or stats[0] > DRIVER_SAMPLES:
        groups = max(1, int(np.ceil(np.sqrt(stats[1] or 1))))
        keep = max(2, int(np.sqrt(parts)), int(stats[0] // DRIVER_SAMPLES) + 1)
        placed = Window.partitionBy("g").orderBy(*names[::-1], "pid")
        thinned = samples.withColumn("g", F.col("pid") % groups).withColumn("r", F.row_number().over(placed) - 1)
        samples = thinned.groupBy("g", F.floor(F.col("r") / keep).alias("b")).agg(
            F.min_by(F.struct(*names), "r").alias("k"), F.sum("weight").alias("weight")
        ).select("k.*", "weight")
    rows = samples.select(*names, "weight").collect()
    words = np.array([r[:-1] for r in rows], np.int64).reshape(len(rows), len(names))
    return _cut(words, np.array([r[-1] for r in rows]), parts)


def splitters_sketch(frame: DataFrame, parts: int) -> np.ndarray:
    """Splitters from a mergeable quantile sketch of the highest word, in the JVM; one-word keys."""
    names = key_names(frame)
    if len(names) != 1:
        raise ValueError("the sketch splits one-word keys")
    sketch = frame.agg(F.kll_sketch_agg_bigint("w0").alias("k"))
    ranks = F.array(*[F.lit(j / parts) for j in range(1, parts)])
    got = sketch.select(F.kll_sketch_get_quantile_bigint("k", ranks)).first()[0]
    return np.array(got, np.int64).reshape(-1, 1)


def place(words: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Number of cuts that are <= each key, by binary search over all rows at once."""
    low, high = np.zeros(len(words), np.int64), np.full(len(words), len(cuts), np.int64)
    while (low < high).any():
        mid = (low + high) // 2
        at = cuts[np.minimum(mid, len(cuts) - 1)]
        le = np.zeros(len(words), bool)
        open_ = np.ones(len(words), bool)
        for k in range(words.shape[1] - 1, -1, -1):
            le |= open_ & (at[:, k] < words[:, k])
            open_ &= at[:, k] == words[:, k]
        le |= open_
        active = low < high
        low = np.where(active & le, mid + 1, low)
        high = np.where(active & ~le, mid, high)
    return low


#: most ranges that are searched by an expression; more are searched in batches
TREE = 256


def _below(names: list[str], cut: np.ndarray) -> Column:
    """Is the key less than the cut?  Highest word first."""
    out = F.lit(False)
    for k, name in enumerate(names):
        c = F.lit(int(cut[k]))
        out = (F.col(name) < c) | ((F.col(name) == c) & out) if k else F.col(name) < c
    return out


def _tree(names: list[str], cuts: np.ndarray, low: int, high: int) -> Column:
    """The number of cuts, between ``low`` and ``high``, that are <= the key, as nested conditions: binary search in generated code."""
    if low == high:
        return F.lit(low)
    mid = (low + high) // 2
    return F.when(_below(names, cuts[mid]), _tree(names, cuts, low, mid)).otherwise(_tree(names, cuts, mid + 1, high))


def route(frame: DataFrame, cuts: np.ndarray, how: str = "tree") -> DataFrame:
    """``frame`` with ``part``, the range its key falls into; other columns stay.

    ``tree``: binary search as an expression, in the JVM, for up to ``TREE`` ranges.  ``search``: binary search in batches.  ``join``: the ranges as a
    broadcast table and a range join, in the JVM.  ``asof``: splitters and keys in one order, each key takes the latest
    splitter (one sorted exchange into one task: a check for small tables).
    """
    names = key_names(frame)
    if not len(cuts):
        return frame.withColumn("part", F.lit(0))
    spark = frame.sparkSession
    if how == "tree" and len(cuts) < TREE:
        return frame.withColumn("part", _tree(names, cuts, 0, len(cuts)))
    if how in ("tree", "search"):
        held = spark.sparkContext.broadcast(cuts)
        schema = T.StructType([*frame.schema.fields, T.StructField("part", T.IntegerType())])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                words = np.stack([batch.column(batch.schema.get_field_index(c)).to_numpy() for c in names], 1)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(place(words, held.value).astype(np.int32))], schema.names)

        return frame.mapInArrow(run, schema)
    order = names[::-1]
    key: Column = F.struct(*order)
    edges = [tuple(int(x) for x in c[::-1]) for c in cuts]
    kinds = ", ".join(f"{c}: bigint" for c in order)
    if how == "join":
        rows = [(lo, hi, i) for i, (lo, hi) in enumerate(zip([None, *edges], [*edges, None], strict=True))]
        ranges = spark.createDataFrame(rows, f"lo struct<{kinds}>, hi struct<{kinds}>, part int")
        inside = (F.col("lo").isNull() | (key >= F.col("lo"))) & (F.col("hi").isNull() | (key < F.col("hi")))
        return frame.join(F.broadcast(ranges), inside).drop("lo", "hi")
    marks = spark.createDataFrame([(e, i + 1) for i, e in enumerate(edges)], f"k struct<{kinds}>, part int").groupBy("k").agg(F.max("part").alias("part"))
    rest = [c for c in frame.columns]
    left = frame.select(F.struct(*rest).alias("row"), key.alias("k"), F.lit(None).cast("int").alias("part"), F.lit(1).alias("o"))
    both = left.unionByName(marks.select(F.lit(None).cast(left.schema["row"].dataType).alias("row"), "k", "part", F.lit(0).alias("o")))
    latest = F.last("part", ignorenulls=True).over(Window.orderBy("k", "o").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("part", F.coalesce(latest, F.lit(0))).where("o = 1").select("row.*", "part")


def exchange(frame: DataFrame, parts: int) -> DataFrame:
    """The one shuffle: rows go to the partition that ``part`` names."""
    return frame.repartitionById(parts, F.col("part"))


def compact(frame: DataFrame, how: str = "adjacent", multiplicity: bool = False) -> DataFrame:
    """Distinct keys of each part, in key order: ``words, part`` [, ``copies``]; no further shuffle.

    ``adjacent``: sorted rows are compared with the one before, across batches.  ``window``: the same in the JVM.  ``agg``: a hash
    aggregate.
    """
    names = key_names(frame)
    order = names[::-1]
    if how == "agg":
        grouped = frame.groupBy(*names, "part")
        return grouped.agg(F.count("*").alias("copies")) if multiplicity else frame.select(*names, "part").dropDuplicates([*names, "part"])
    if how == "window":
        inside = Window.partitionBy("part", *names).orderBy(*order)
        if multiplicity:
            return frame.withColumn("copies", F.count("*").over(Window.partitionBy("part", *names))).withColumn("_r", F.row_number().over(inside)).where("_r = 1").select(*names, "part", "copies")
        return frame.withColumn("_r", F.row_number().over(inside)).where("_r = 1").select(*names, "part")
    kept = frame.select(*names, "part").sortWithinPartitions("part", *order)
    schema = T.StructType([*kept.schema.fields, *([T.StructField("copies", T.LongType())] if multiplicity else [])])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None  # last key and its copies so far; it may go on in the next batch
        for batch in batches:
            rows = _matrix(batch)
            if not len(rows):
                continue
            if held is not None:
                rows, copies = np.concatenate([held[0][None, :], rows]), np.concatenate([[held[1]], np.ones(len(rows), np.int64)])
            else:
                copies = np.ones(len(rows), np.int64)
            starts = np.flatnonzero(np.concatenate([[True], (rows[1:] != rows[:-1]).any(1)]))
            totals = np.add.reduceat(copies, starts)
            held = rows[starts[-1]], int(totals[-1])
            if len(starts) > 1:
                yield emit(rows[starts[:-1]], totals[:-1])
        if held is not None:
            yield emit(held[0][None, :], np.array([held[1]]))

    def emit(rows: np.ndarray, totals: np.ndarray) -> pa.RecordBatch:
        columns = [pa.array(np.ascontiguousarray(rows[:, k])) for k in range(len(names))] + [pa.array(rows[:, -1].astype(np.int32))]
        return pa.RecordBatch.from_arrays([*columns, *([pa.array(totals)] if multiplicity else [])], schema.names)

    return kept.mapInArrow(run, schema)


def boundary(unique: DataFrame) -> DataFrame:
    """First and last key of each part, two per part."""
    names = key_names(unique)
    key = F.struct(*names[::-1])
    return unique.groupBy("part").agg(F.min(key).alias("first"), F.max(key).alias("last"), F.count("*").alias("rows")).orderBy("part")


def boundary_duplicates(unique: DataFrame) -> int:
    """Keys that end one part and begin the next: zero, as ranges are half open."""
    edge = [r for r in boundary(unique).collect() if r["rows"]]
    return sum(a["last"] == b["first"] for a, b in zip(edge, edge[1:], strict=False))


def range_laid(frame: DataFrame, parts: int, s: int | None = None, compact_how: str = "adjacent", levels: int = 1, local_first: bool = True) -> tuple[DataFrame, np.ndarray]:
    """``(words, part)`` of the distinct keys, part = key range, and the cuts, by which other tables can be laid out the same way.

    Keys are sorted once, into runs that both the sampling and the exchange read.
    """
    keys = require(frame, key_names(frame)).select(*key_names(frame))
    runs = sorted_runs(keys, distinct=local_first)
    cuts = splitters(sample_runs(runs, s or min(8 * parts, SAMPLES)), parts, levels)
    return compact(exchange(route(runs, cuts), parts), compact_how), cuts


def range_sampled(frame: DataFrame, parts: int, s: int | None = None, compact_how: str = "adjacent", levels: int = 1, local_first: bool = True, rebalance: str | None = None) -> DataFrame:
    """The distinct keys of ``range_laid``.

    ``rebalance='unique'`` chooses the ranges by the distinct keys of the parts and not by the rows exchanged: the compacted
    set is cut anew at exact ranks.
    """
    unique, _ = range_laid(frame, parts, s, compact_how, levels, local_first)
    return rebalanced(staged(unique, "unique"), parts) if rebalance == "unique" else unique


def range_presampled(frame: DataFrame, sample: DataFrame, parts: int, s: int | None = None, compact_how: str = "agg") -> DataFrame:
    """Like ``range_sampled`` with splitters from another table, such as the keys of a sample of the sources: nothing is staged and the keys are made once.

    The splitters only set the balance; the result is the same for any.
    """
    cuts = splitters(regular_sample(sample, s or min(8 * parts, SAMPLES)), parts)
    return compact(exchange(route(frame.select(*key_names(frame)), cuts), parts), compact_how)


def rebalanced(unique: DataFrame, parts: int) -> DataFrame:
    """Contiguous parts of equal numbers of keys (at most one apart): exact ranks from the counts of the old parts."""
    names = key_names(unique)
    counts = {r["part"]: r["count"] for r in unique.groupBy("part").count().collect()}
    total, before, offsets = sum(counts.values()), 0, []
    for p in sorted(counts):
        offsets.append((p, before))
        before += counts[p]
    start = unique.sparkSession.createDataFrame(offsets or [(0, 0)], "part int, _b long")
    rank = F.row_number().over(Window.partitionBy("part").orderBy(*names[::-1])) - 1
    ranked = unique.withColumn("_r", rank).join(F.broadcast(start), "part")
    fresh = F.floor((F.col("_b") + F.col("_r")) * parts / F.lit(max(total, 1))).cast("int")
    return exchange(ranked.select(*names, F.least(fresh, F.lit(parts - 1)).alias("part")), parts)


def range_native(frame: DataFrame, parts: int) -> DataFrame:
    """The engine's own sampled ranges, then distinct: range partitioning already meets the aggregate's need, so one exchange."""
    names = key_names(frame)
    return frame.select(*names).repartitionByRange(parts, *[F.col(c) for c in names[::-1]]).dropDuplicates(names)


def report(frame: DataFrame, parts: int, s: int | None = None, levels: int = 1) -> DedupReport:
    """Run the method step by step and count what each step moves."""
    names = key_names(frame)
    s = s or min(8 * parts, SAMPLES)
    keys = staged(frame.select(*names), "keys")
    generated = keys.count()
    base = sorted_runs(keys, distinct=True)
    rows = base.count()
    samples = staged(sample_runs(base, s), "samples")
    cuts = splitters(samples, parts, levels)
    routed = staged(route(base, cuts), "routed")
    sent = routed.groupBy("part").agg(F.count("*").alias("exchanged"))
    unique = staged(compact(exchange(routed, parts)), "unique")
    left = unique.groupBy("part").agg(F.count("*").alias("unique"))
    ids = frame.sparkSession.range(parts).select(F.col("id").cast("int").alias("part"))
    counts = ids.join(sent, "part", "left").join(left, "part", "left").na.fill(0)
    return DedupReport(generated, generated - rows, rows, unique.count(), samples.count(), boundary_duplicates(unique), counts)


def regular_sample_by(frame: DataFrame, group: str, s: int) -> DataFrame:
    """Regular sampling inside the groups of a column, in the JVM: ``group, words, weight``."""
    names = key_names(frame)
    ranked = frame.select(group, *names).withColumn("_r", F.row_number().over(Window.partitionBy(group).orderBy(*names[::-1])) - 1)
    ranked = ranked.withColumn("_d", F.count("*").over(Window.partitionBy(group)))
    k = F.ceil(F.col("_r") * s / F.col("_d"))  # the first k whose place is not before this row
    chosen = ranked.where((F.col("_d") < s) | ((k < s) & (F.floor(k * F.col("_d") / s) == F.col("_r"))))
    return chosen.select(group, *names, (F.col("_d") / F.least(F.col("_d"), F.lit(s))).alias("weight"))
