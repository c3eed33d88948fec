"""WARC archives: writing with revisit records, and reading back by boundary-chain verification.

A WARC record is a header, an empty line, a payload of the declared length and two line ends.  The mark that starts a record
may as well stand inside a payload, so a reader that starts anywhere can't trust it.  Here the archive is read in pieces
between marks.  Every mark is a candidate record, and its header gives the offset of its successor.  Chains are followed by
pointer jumping from the file's start; only candidates on the chain are records.

Chains are first followed inside blocks of ``BLOCK`` bytes, each in one task.  What is left are jumps from one block into
another, of which a file has few; those are doubled as joins until nothing new is reached.
"""

from __future__ import annotations

import base64
import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from detspark.plans.scratch import fresh_path, staged

#: fixed by the format
MARK = "WARC/1.0\r\n"
TAIL = "\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.0/revisit/identical-payload-digest"
BLOCK = 1 << 26


def base32_sha1(data: Column) -> Column:
    """Bare upper-case base32 of the SHA-1 of a binary column: four digits for every 20 bits of the hex form."""
    text = F.sha1(data)
    groups = [F.lpad(F.conv(F.substring(text, 5 * i + 1, 5), 16, 32), 4, "0") for i in range(8)]
    return F.translate(F.concat(*groups), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def decided(pages: DataFrame, least: int = 0) -> DataFrame:
    """``(page_id, url, html)`` with ``_digest``, ``_bytes`` and ``_refers``: the largest page_id of equal payloads of at least ``least`` bytes, if another's.

    Only digests and ids are grouped, in pre-aggregated form, and only the few rows of a digest go back to the pages, so a
    payload that a third of the pages share makes no large group.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    marked = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), base32_sha1(payload).alias("_digest"), F.octet_length(payload).cast("long").alias("_bytes"))
    last = marked.where(F.col("_bytes") >= least).groupBy("_digest").agg(F.max("page_id").alias("_last"), F.count("*").alias("_n")).where("_n > 1")
    joined = marked.join(last.select(F.col("_digest").alias("_d"), "_last"), F.col("_digest") == F.col("_d"), "left")
    refers = F.when(~F.col("page_id").eqNullSafe(F.col("_last")), F.col("_last"))
    return joined.select("page_id", "url", "html", "_digest", "_bytes", refers.alias("_refers"))


def _urn(column: str) -> Column:
    return F.concat(F.lit("<urn:page:"), F.col(column).cast("string"), F.lit(">"))


def write(pages: DataFrame, path: str, least: int = 0, compression: str = "none", records_per_file: int = 200_000) -> None:
    """Write one record per page below ``path``: a response with its payload, or a revisit without it.

    The text sink with the record end as its line separator writes the files, so any file system of Spark takes them.  Line
    ends and tabs in a url become spaces.  A null page_id is written as ``null``, a null html or url as empty; an empty table
    gives files without records; rows that repeat a page_id each give a record.
    """
    page = decided(pages, least)
    name = F.coalesce(F.col("page_id").cast("string"), F.lit("null"))
    block = F.when(F.col("_refers").isNull(), F.col("html")).otherwise(F.lit(""))
    lines = [
        F.lit("WARC/1.0"),
        F.concat(F.lit("WARC-Type: "), F.when(F.col("_refers").isNull(), "response").otherwise("revisit")),
        F.concat(F.lit("WARC-Record-ID: <urn:page:"), name, F.lit(">")),
        F.concat(F.lit("WARC-Target-URI: "), F.regexp_replace(F.coalesce("url", F.lit("")), r"[\r\n\t]", " ")),
        F.lit("WARC-Date: 1970-01-01T00:00:00Z"),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("_digest")),
        F.when(F.col("_refers").isNotNull(), F.concat(F.lit(f"WARC-Profile: {PROFILE}\r\nWARC-Refers-To: "), _urn("_refers"))),
        F.lit("Content-Type: text/html"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    ]
    record = F.concat(F.concat_ws("\r\n", *lines), F.lit(TAIL), block)
    page.select(record.alias("value")).write.option("lineSep", TAIL).option("compression", compression).option("maxRecordsPerFile", records_per_file).text(path)


def _field(header: str, name: str) -> Column:
    return F.regexp_extract(header, rf"(?:^|\r\n){name}: *([^\r\n]*)", 1)


def _pieces(spark, path: str) -> DataFrame:
    """What lies between marks.

    ``_part`` and ``_row`` order the pieces of a file within one evaluation only: they follow the split sizes, which follow the cores
    there are.  ``_h1, _h2`` name a piece by what it holds, in any evaluation.
    """
    raw = spark.read.option("lineSep", MARK).text(path)
    raw = raw.select("value", F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("_part"))
    return raw.withColumn("_row", F.monotonically_increasing_id()).withColumns({"_h1": F.xxhash64("value"), "_h2": F.xxhash64(F.lit(1), "value")})


def candidates(spark, path: str) -> DataFrame:
    """Every piece of the archives: its length, its jump to the successor its header names, header fields, and the payload's digest where that lies whole before the next mark."""
    cut = F.instr("value", TAIL)
    head = F.when(cut > 0, F.left("value", cut - 1)).otherwise(F.lit(""))
    piece = _pieces(spark, path).withColumn("_n", F.octet_length("value").cast("long")).withColumn("_head", head).withColumn("_ends", cut > 0)
    piece = piece.withColumn("_length", F.when(F.col("_ends"), F.regexp_extract("_head", r"(?:^|\r\n)Content-Length: *(\d{1,15}) *(?:\r|$)", 1).try_cast("long")))
    piece = piece.withColumn("_at", F.octet_length("_head").cast("long") + len(TAIL))
    whole = F.col("_ends") & (F.col("_n") == F.col("_at") + F.col("_length") + len(TAIL))
    payload = F.substring(F.col("value").cast("binary"), (F.col("_at") + 1).cast("int"), F.col("_length").cast("int"))
    return piece.select(
        "file", "_part", "_row", "_h1", "_h2", "_n", "_at", "_length",
        (F.col("_at") + F.col("_length") + len(TAIL) + len(MARK)).alias("_jump"),
        _field("_head", "WARC-Type").alias("kind"), _field("_head", "WARC-Record-ID").alias("name"), _field("_head", "WARC-Refers-To").alias("refers"),
        F.regexp_extract(_field("_head", "WARC-Payload-Digest"), "sha1:(.*)", 1).alias("declared"),
        F.when(whole, base32_sha1(payload)).alias("_digest"),
    )


def _summed(pieces: DataFrame) -> DataFrame:
    """Pieces with ``_nth``, their place in the file from 1, and ``_sum``, the bytes up to and with each.

    Splits of a file are summed in parallel and then offset by those before, so a large archive is no single task.
    """
    inside = Window.partitionBy("file", "_part").orderBy("_row")
    local = pieces.withColumn("_i", F.row_number().over(inside)).withColumn("_s", F.sum("_n").over(inside))
    before = Window.partitionBy("_of").orderBy("_from").rowsBetween(Window.unboundedPreceding, -1)
    splits = pieces.groupBy(F.col("file").alias("_of"), F.col("_part").alias("_from")).agg(F.count("*").alias("_c"), F.sum("_n").alias("_b"))
    offsets = splits.select("_of", "_from", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_c0"), F.coalesce(F.sum("_b").over(before), F.lit(0)).alias("_b0"))
    joined = local.join(offsets, (F.col("file") == F.col("_of")) & (F.col("_part") == F.col("_from")))
    return joined.select(*pieces.columns, (F.col("_c0") + F.col("_i")).alias("_nth"), (F.col("_b0") + F.col("_s")).alias("_sum"))


def _inside(frame: pd.DataFrame, width: int) -> pd.DataFrame:
    """Follow the chains of one block: where does each candidate's chain leave it?  -1: at no candidate or the file's end."""
    off, succ = frame["off"].to_numpy(), frame["succ"].fillna(-1).to_numpy().astype(np.int64)
    order = np.argsort(off, kind="stable")
    off, succ = off[order], succ[order]
    block = off[0] // width
    at = np.searchsorted(off, succ)
    hit = (at < len(off)) & (off[np.minimum(at, len(off) - 1)] == succ)
    end = np.arange(len(off))
    step = np.where(hit, at, end)
    while True:  # double the step until every chain has stopped
        twice = step[step]
        if (twice == step).all():
            break
        step = twice
    leaves = succ[step]
    leaves = np.where(leaves // width > block, leaves, -1)
    return pd.DataFrame({"file": frame["file"].iloc[0], "off": off, "succ": succ, "leaves": leaves})


def _reached(key: tuple, frame: pd.DataFrame, entries: pd.DataFrame) -> pd.DataFrame:
    """Mark what the block's entry points reach, and name the record that each piece belongs to."""
    if not len(frame):
        return pd.DataFrame({"file": np.array([], object), "off": np.array([], np.int64), "record": np.array([], np.int64)})
    frame = frame.sort_values("off")
    off, succ = frame["off"].to_numpy(), frame["succ"].to_numpy()
    at = np.searchsorted(off, succ)
    hit = (at < len(off)) & (off[np.minimum(at, len(off) - 1)] == succ)
    mark = np.isin(off, entries["off"].to_numpy())
    step, live = np.where(hit, at, 0), hit
    while True:
        new = mark.copy()
        new[step[mark & live]] = True
        if (new == mark).all() and not live.any():
            break
        mark, live, step = new, live & live[step], step[step]
    owner = np.maximum.accumulate(np.where(mark, np.arange(len(off)), -1))
    return pd.DataFrame({"file": frame["file"].to_numpy(), "off": off, "record": np.where(owner >= 0, off[np.maximum(owner, 0)], -1)})


def verified(chain: DataFrame, width: int = BLOCK) -> DataFrame:
    """Candidates ``(file, off, succ)`` → ``(file, off, record)``: the record that holds each, itself if it is one.

    ``record`` is -1 for pieces that belong to a record of an earlier block.
    """
    blocked = chain.withColumn("_blk", F.floor(F.col("off") / width))
    jumps = staged(blocked.groupBy("file", "_blk").applyInPandas(lambda frame: _inside(frame, width), "file string, off long, succ long, leaves long"), "jumps")
    across = jumps.where("leaves >= 0").select("file", "leaves").distinct().withColumnRenamed("leaves", "off")
    starts = jumps.where("off = 0").select("file", "off")
    doors = jumps.join(starts.unionByName(across).distinct(), ["file", "off"]).select("file", "off", "leaves")
    hop = staged(doors.where("leaves >= 0"), "hops")
    reached = starts
    known = None
    while True:  # entry points reached after 1, 2, 4, ... hops
        new = reached.unionByName(reached.join(hop, ["file", "off"]).select("file", F.col("leaves").alias("off"))).distinct()
        reached = staged(new, "reached")
        count = reached.count()
        if count == known:
            break
        known = count
        far = hop.select("file", F.col("off").alias("leaves"), F.col("leaves").alias("_far"))
        hop = staged(hop.join(far, ["file", "leaves"]).select("file", "off", F.col("_far").alias("leaves")).unionByName(hop.join(far, ["file", "leaves"], "left_anti").select("file", "off", "leaves")), "hops")
    doors_in = reached.withColumn("_blk", F.floor(F.col("off") / width))
    left = jumps.withColumn("_blk", F.floor(F.col("off") / width))
    found = left.groupBy("file", "_blk").cogroup(doors_in.groupBy("file", "_blk")).applyInPandas(_reached, "file string, off long, record long")
    found = staged(found.withColumn("_blk", F.floor(F.col("off") / width)), "owners")
    # a block's first pieces belong to the last record of the blocks before
    over = Window.partitionBy("_of").orderBy("_in").rowsBetween(Window.unboundedPreceding, -1)
    last = found.groupBy(F.col("file").alias("_of"), F.col("_blk").alias("_in")).agg(F.max("record").alias("_r")).select("_of", "_in", F.max("_r").over(over).alias("_last"))
    joined = found.join(last, (F.col("file") == F.col("_of")) & (F.col("_blk") == F.col("_in")))
    return joined.select("file", "off", F.greatest("record", F.coalesce("_last", F.lit(-1))).alias("record"))


def read(spark, path: str, width: int = BLOCK) -> DataFrame:
    """Records of the archives below ``path``: ``file, off, kind, name, refers, declared, payload_bytes, payload_digest``.

    The digest is taken from the payload as read.  Marks inside payloads give no records; bytes after the last record of a
    chain that don't lead on are not read.  Files without a record at their start give none, nor do empty files.  Records that
    repeat an id, in one file or several, each come out.  ``width`` is the block width.

    Archives are scanned a second time only for payloads that hold marks.  Splits may then be cut differently, so pieces are
    found again by what they hold.
    """
    piece = staged(candidates(spark, path), "warc-pieces")
    numbers = _summed(piece.select("file", "_part", "_row", "_n", "_jump"))
    # piece k (from 1) starts after k - 1 marks; the first is what stands before the first mark
    placed = numbers.where("_nth > 1").withColumn("off", F.col("_sum") - F.col("_n") + len(MARK) * (F.col("_nth") - 2))
    # a file that does not start with a mark has no record at 0
    lead = numbers.where("_nth = 1 and _n > 0").select("file")
    placed = placed.join(lead, "file", "left_anti")
    placed = staged(placed.select("file", "_part", "_row", "off", (F.col("off") + F.col("_jump")).alias("succ")), "warc-offsets")
    owner = verified(placed.select("file", "off", "succ"), width)
    known = placed.join(owner, ["file", "off"]).where("record >= 0").select("file", "_part", "_row", "off", "record")
    full = staged(known.join(piece, ["file", "_part", "_row"]), "warc-known")
    simple = full.where("off = record and _digest is not null")
    simple = simple.select("file", "off", "kind", "name", "refers", "declared", F.col("_length").alias("payload_bytes"), F.col("_digest").alias("payload_digest"))
    broken = full.where("off = record and _digest is null").select("file", "record")
    parts = staged(full.join(broken, ["file", "record"], "left_semi"), "warc-parts")
    if parts.isEmpty():
        return simple
    again = _pieces(spark, path).select("_h1", "_h2", F.col("value").cast("binary").alias("_raw"))
    again = again.join(parts.select("_h1", "_h2").distinct(), ["_h1", "_h2"], "left_semi").groupBy("_h1", "_h2").agg(F.first("_raw").alias("_raw"))
    return simple.unionByName(_glued(parts.join(again, ["_h1", "_h2"])))


def _glued(parts: DataFrame) -> DataFrame:
    """Records whose payload holds marks, from their pieces; a group is one record."""
    mark = MARK.encode()

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values("off")
        head = frame.iloc[0]
        body = mark.join(bytes(x) for x in frame["_raw"])
        payload = body[int(head["_at"]) : int(head["_at"]) + int(head["_length"])]
        fields = {c: [head[c]] for c in ("kind", "name", "refers", "declared")}
        digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
        return pd.DataFrame({"file": [head["file"]], "off": [head["record"]], **fields, "payload_bytes": [len(payload)], "payload_digest": [digest]})

    schema = "file string, off long, kind string, name string, refers string, declared string, payload_bytes long, payload_digest string"
    return parts.groupBy("file", "record").applyInPandas(run, schema)


def resolved(records: DataFrame) -> DataFrame:
    """Records with a revisit's payload length and digest taken from the response that it refers to."""
    responses = records.where("kind = 'response'").select(F.col("name").alias("_name"), F.col("payload_digest").alias("_got"), F.col("payload_bytes").alias("_size")).distinct()
    same = (F.col("refers") == F.col("_name")) & (F.col("declared") == F.col("_got"))
    again = records.where("kind = 'revisit'").join(responses, same, "left")
    again = again.select("file", "off", "kind", "name", "refers", "declared", F.col("_size").alias("payload_bytes"), F.col("_got").alias("payload_digest"))
    return records.where("kind <> 'revisit'").unionByName(again)


def op2_warc(spark, sf_dir: str) -> DataFrame:
    """Every row of ``pages`` as the archives written from it give it back: size and digest of its whole payload (null html: empty), and
    whether it is a response or a revisit of an equal payload.

    A null page_id comes back as null.  Rows that repeat a page_id each have a record, but a revisit can only name the id.
    """
    path = fresh_path(spark, "warc")
    write(spark.read.parquet(f"{sf_dir}/pages.parquet"), path, compression="gzip")
    number = lambda c: F.regexp_extract(c, "^<urn:page:(-?[0-9]+)>$", 1).try_cast("long")
    return resolved(read(spark, path)).select(
        number("name").alias("page_id"), "payload_bytes", "payload_digest", F.col("kind").alias("record_type"), number("refers").alias("refers_to")
    )

