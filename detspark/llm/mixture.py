"""Mixing sources to target weights, with DataFrame operations only.

The words of a source form one stream: its documents in a fixed order.  The stream is cut into blocks of a fixed number of
words.  The mix is a sequence of output shards of as many slots; every shard draws how many slots each source gets from a
multinomial distribution, and a source's slots map to its blocks through a pseudorandom permutation of the block numbers,
a new one for every pass over the source.  Blocks are then joined by (source, number).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from detspark.llm import text as tx
from detspark.plans.scratch import staged

#: fixed by the contract: what a word is, and the cap on repeats
WORD = r"[^\x20\x09-\x0D]+"
PASSES = 3


@dataclass(frozen=True)
class MixConfig:
    block_words: int = 16
    shard_slots: int = 65_536
    buckets: int = 1024
    rounds: int = 16
    seed: int = 42
    cells: int = 4096
    broadcast_sources: int = 1 << 16


def placed(docs: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """``docs`` with ``_src`` (source), ``_size`` (words) and ``_start``, the words before it in its source's stream.

    Running sums are taken inside hash buckets of a source and offset by the sums of the buckets before, so a source with
    most of the rows is still dealt over ``buckets`` tasks.  The order is by bucket, id, size and a hash of the row.
    """
    sized = docs.withColumn("_src", F.col("source")).withColumn("_size", F.coalesce(F.regexp_count("text", F.lit(WORD)), F.lit(0)).cast("long"))
    sized = sized.withColumn("_bkt", F.pmod(F.xxhash64("doc_id", F.lit(cfg.seed)), F.lit(cfg.buckets)).cast("int"))
    sized = sized.withColumn("_tie", F.xxhash64("text"))
    sums = sized.groupBy("_src", "_bkt").agg(F.sum("_size").alias("_n"))
    before = F.sum("_n").over(Window.partitionBy("_src").orderBy("_bkt").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sums.select(F.col("_src").alias("_os"), F.col("_bkt").alias("_ob"), F.coalesce(before, F.lit(0)).alias("_off"))
    inside = F.sum("_size").over(Window.partitionBy("_src", "_bkt").orderBy("doc_id", "_size", "_tie").rowsBetween(Window.unboundedPreceding, -1))
    local = sized.withColumn("_in", F.coalesce(inside, F.lit(0)))
    joined = local.join(offsets, F.col("_src").eqNullSafe(F.col("_os")) & (F.col("_bkt") == F.col("_ob")))
    return joined.withColumn("_start", (F.col("_off") + F.col("_in")).cast("long")).drop("_os", "_ob", "_off", "_in", "_bkt", "_tie")


def targets(sizes: DataFrame) -> DataFrame:
    """``(_src, source_size)`` → also ``_weight`` and ``target``; one row per source.

    Sources by code point, null last, weigh 1, 2, 3, 1, 2, 3 …  They share the total by weight, no source above ``PASSES``
    times its size, the excess shared anew: with caps ordered by cap / weight, the capped sources are the first ones, until
    the level of the rest is no higher than the next cap.
    """
    everyone = Window.orderBy(F.col("_src").isNull(), "_src")
    ranked = sizes.withColumn("_weight", ((F.row_number().over(everyone) - 1) % 3 + 1).cast("double"))
    ranked = ranked.withColumn("_cap", (F.lit(PASSES) * F.col("source_size")).cast("double"))
    rising = Window.orderBy(F.col("_cap") / F.col("_weight"), F.col("_src").isNull(), "_src")
    all_of = Window.partitionBy()
    level = (F.sum("source_size").over(all_of) - F.coalesce(F.sum("_cap").over(rising.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))) / F.sum("_weight").over(
        rising.rowsBetween(0, Window.unboundedFollowing)
    )
    free = ranked.withColumn("_level", level).withColumn("_open", F.col("_level") * F.col("_weight") <= F.col("_cap"))
    settled = free.withColumn("_final", F.min(F.when(F.col("_open"), F.struct(F.col("_cap") / F.col("_weight"), F.col("_level").alias("l")))).over(all_of)["l"])
    return settled.select("_src", "source_size", "_weight", F.coalesce(F.least("_cap", F.col("_final") * F.col("_weight")), F.lit(0.0)).alias("target"))


def permuted(index: Column, size: Column, *keys: Column, rounds: int) -> Column:
    """A pseudorandom permutation of 0..size-1 under ``keys``: each round either keeps x or swaps it with (k - x) mod size.

    Both members of a pair see the same coin, the hash of the larger, so every round is its own inverse.
    """

    def turn(x: Column, r: Column) -> Column:
        other = F.pmod(F.pmod(F.xxhash64(r, *keys), size) - x, size)
        return F.when(F.xxhash64(F.greatest(x, other), r, F.lit(1), *keys) % 2 == 0, other).otherwise(x)

    return F.aggregate(F.sequence(F.lit(0), F.lit(rounds - 1)), index, turn)


def shard_counts(sources: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """Sources ``(_src, source_size, target)`` → ``(_shard, _src, _blocks, _count)``: each output shard's multinomial draw; no row for 0.

    Every slot draws its source on its own, by the hash of its number, with probabilities in proportion to the blocks that
    reach the targets.  A slot finds its source through the cell of 0..1 that its draw falls into, and only counts per task,
    shard and source are shuffled.  Sources are few; more than ``broadcast_sources`` are not broadcast.
    """
    spark = sources.sparkSession
    used = sources.where("source_size > 0").withColumn("_blocks", F.ceil(F.col("source_size") / F.lit(cfg.block_words)).cast("long"))
    used = used.withColumn("_want", F.col("target") * F.col("_blocks") / F.col("source_size"))
    used = staged(used.select("_src", "_blocks", "_want"), "sources")
    many, total = used.agg(F.count("*"), F.sum("_want")).first()
    everyone = Window.orderBy(F.col("_src").isNull(), "_src")
    last = F.row_number().over(everyone) == many
    high = F.when(last, F.lit(1.0)).otherwise(F.sum("_want").over(everyone.rowsBetween(Window.unboundedPreceding, 0)) / F.lit(total or 1.0))
    ranges = used.withColumn("_high", high).withColumn("_low", F.coalesce(F.lag("_high").over(everyone), F.lit(0.0)))
    cell = lambda u: F.least(F.floor(u * cfg.cells), F.lit(cfg.cells - 1)).cast("int")
    ranges = staged(ranges.withColumn("_cell", F.explode(F.sequence(cell(F.col("_low")), cell(F.col("_high"))))).select("_cell", "_low", "_high", "_src", "_blocks"), "cells")
    draw = F.shiftrightunsigned(F.xxhash64(F.lit(cfg.seed), F.lit("draw"), "id"), 11) / float(1 << 53)
    drawn = spark.range(int(round(total or 0.0))).select(F.floor(F.col("id") / cfg.shard_slots).alias("_shard"), draw.alias("_u")).withColumn("_at", cell(F.col("_u")))
    inside = (F.col("_at") == F.col("_cell")) & (F.col("_u") >= F.col("_low")) & (F.col("_u") < F.col("_high"))
    return drawn.join(F.broadcast(ranges) if many <= cfg.broadcast_sources else ranges, inside).groupBy("_shard", "_src", "_blocks").agg(F.count("*").alias("_count"))


def slot_blocks(slots: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """Runs of slots ``(_src, _blocks, _from, _upto)`` of a source, ``_upto`` excluded → ``(_src, _slot, _block)``, the block that each slot takes."""
    # dealt anew: a few rows become very many, and their number is not known to the planner
    parts = int(slots.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = slots.where("_from < _upto").repartition(parts, "_src", "_from")
    one = dealt.withColumn("_slot", F.explode(F.sequence(F.col("_from"), F.col("_upto") - 1))).withColumn("_pass", F.floor(F.col("_slot") / F.col("_blocks")))
    block = permuted(F.col("_slot") % F.col("_blocks"), F.col("_blocks"), F.coalesce(F.col("_src"), F.lit("")), F.col("_src").isNull(), F.col("_pass"), F.lit(cfg.seed), rounds=cfg.rounds)
    return one.select("_src", "_slot", block.alias("_block"))


def block_counts(sources: DataFrame, cfg: MixConfig = MixConfig()) -> tuple[DataFrame, DataFrame]:
    """Sources with targets → (``(_src, _whole)``, ``(_src, _block)``): passes that take every block, and the blocks of the pass after them.

    A source's slots are numbered over its shards and stop at ``PASSES`` passes over its blocks.  A permutation takes each
    block once in a whole pass, so only the slots of the last pass are mapped one by one.
    """
    counts = staged(shard_counts(sources, cfg), "draws")
    sums = counts.groupBy("_src", "_blocks").agg(F.sum("_count").alias("_n")).withColumn("_n", F.least("_n", F.col("_blocks") * PASSES))
    sums = staged(sums.withColumn("_whole", F.floor(F.col("_n") / F.col("_blocks"))), "draw-sums")
    by_source = Window.partitionBy("_src").orderBy("_shard").rowsBetween(Window.unboundedPreceding, -1)
    runs = counts.withColumn("_base", F.coalesce(F.sum("_count").over(by_source), F.lit(0).cast("long")))
    limits = sums.select(F.col("_src").alias("_ls"), "_n", "_whole")
    runs = runs.join(limits, F.col("_src").eqNullSafe(F.col("_ls")))
    runs = runs.select("_src", "_blocks", F.greatest("_base", F.col("_whole") * F.col("_blocks")).alias("_from"), F.least(F.col("_base") + F.col("_count"), "_n").alias("_upto"))
    return sums.select("_src", "_whole"), slot_blocks(runs, cfg).select("_src", "_block")


def cut_blocks(rows: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """Rows with ``_start`` and ``_size`` > 0, one per block they reach into: ``_block``, ``_from`` (word in the row), ``_len``."""
    b = F.lit(cfg.block_words)
    first, last = F.floor(F.col("_start") / b), F.floor((F.col("_start") + F.col("_size") - 1) / b)
    out = rows.where("_size > 0").withColumn("_block", F.explode(F.sequence(first, last)))
    low = F.greatest(F.col("_start"), F.col("_block") * b)
    high = F.least(F.col("_start") + F.col("_size"), (F.col("_block") + 1) * b)
    return out.withColumn("_from", low - F.col("_start")).withColumn("_len", high - low)


def mixed(docs: DataFrame, cfg: MixConfig = MixConfig()) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows, sources, taken) of a mix of ``docs(doc_id, source, text)``.

    rows: ``doc_id, _src, _size, _start``, staged; sources: as ``targets``; taken: ``_src, _start, _block, _from, _len,
    _times`` for each block of a row with words (``_times`` 0 if the mix leaves it).  ``(_src, _start)`` names a row with words.
    A null text has no words; null ids, null sources and repeated rows count as they are; empty input gives empty tables.
    """
    rows = staged(placed(docs.select("doc_id", "source", "text"), cfg).select("doc_id", "_src", "_size", "_start"), "mix-rows")
    sources = staged(targets(rows.groupBy("_src").agg(F.sum("_size").alias("source_size"))), "mix-targets")
    whole, last = block_counts(sources, cfg)
    last = last.select(F.col("_src").alias("_cs"), F.col("_block").alias("_cb"), F.lit(1).alias("_once"))
    passes = whole.select(F.col("_src").alias("_ps"), "_whole")
    sized = rows.select("_src", "_size", "_start").join(passes, F.col("_src").eqNullSafe(F.col("_ps")), "left").drop("_ps")
    cut = cut_blocks(sized, cfg)
    # merge hints: sizes after an explode are underestimated, and neither side may be broadcast
    taken = cut.join(last.hint("merge"), F.col("_src").eqNullSafe(F.col("_cs")) & (F.col("_block") == F.col("_cb")), "left")
    return rows, sources, taken.select("_src", "_start", "_block", "_from", "_len", (F.coalesce("_whole", F.lit(0)) + F.coalesce("_once", F.lit(0))).cast("long").alias("_times"))


def op9_mixture(spark, sf_dir: str) -> DataFrame:
    """Every row of ``documents`` with its size in words, its source's size and target, and the words that the mix takes of it, repeats counted.

    A null or empty text has size 0 and gives nothing; null and repeated ids are rows as any; null sources are one source; an
    empty table gives no rows.
    """
    rows, sources, taken = mixed(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    sums = taken.groupBy("_src", "_start").agg(F.sum(F.col("_len") * F.col("_times")).alias("_taken")).select(F.col("_src").alias("_ts"), F.col("_start").alias("_tt"), "_taken")
    with_words = rows.join(sums.hint("merge"), F.col("_src").eqNullSafe(F.col("_ts")) & (F.col("_start") == F.col("_tt")) & (F.col("_size") > 0), "left")
    marks = sources.select(F.col("_src").alias("_ms"), "source_size", "target")
    out = with_words.join(marks, F.col("_src").eqNullSafe(F.col("_ms")))
    return out.select("doc_id", F.col("_size").alias("size"), F.col("source_size").cast("long").alias("source_size"), "target", F.coalesce("_taken", F.lit(0)).cast("long").alias("taken"))


def mix_documents(docs: DataFrame, cfg: MixConfig = MixConfig()) -> DataFrame:
    """``docs`` as the mix has them, same columns: each row's text is the words of its taken blocks.

    A row whose blocks are all taken once keeps its text as it is; otherwise pass k adds the words of the blocks taken k
    times or more, joined by single spaces, passes joined by line breaks.  Rows of which nothing is taken go, and so do those
    without words.  ``n_chars`` follows the text.  Other columns may have any name; an empty table stays empty.
    """
    used = "doc_id", "source", "text"
    whole = placed(tx.carried(docs, *used), cfg)
    _, _, taken = mixed(docs, cfg)
    runs = taken.groupBy("_src", "_start").agg(
        F.sort_array(F.collect_list(F.struct("_from", "_len", "_times"))).alias("_runs"), F.min("_times").alias("_least"), F.max("_times").alias("_most")
    ).where("_most > 0").select(F.col("_src").alias("_ts"), F.col("_start").alias("_tt"), "_runs", "_least", "_most")
    joined = whole.where("_size > 0").join(runs.hint("merge"), F.col("_src").eqNullSafe(F.col("_ts")) & (F.col("_start") == F.col("_tt")))
    words = F.regexp_extract_all("text", F.lit(f"({WORD})"), F.lit(1))

    def one_pass(k: Column) -> Column:
        kept = F.filter("_runs", lambda r: r["_times"] >= k)
        return F.concat_ws(" ", F.flatten(F.transform(kept, lambda r: F.slice(F.col("_words"), (r["_from"] + 1).cast("int"), r["_len"].cast("int")))))

    mixed_text = F.concat_ws("\n", F.transform(F.sequence(F.lit(1).cast("long"), F.col("_most")), one_pass))
    same = (F.col("_least") == 1) & (F.col("_most") == 1)
    # an explode of one element: the words are formed once per row, and not anew for each run of them
    joined = joined.withColumn("_words", F.explode(F.array(F.when(~same, words))))
    done = joined.withColumn("_new", F.when(same, F.col("text")).otherwise(mixed_text))
    return done.select(*tx.unpacked(docs, {"text": F.col("_new"), "n_chars": F.length("_new")}, used))
