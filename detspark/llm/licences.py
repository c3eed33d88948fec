"""Licence scans: normalised text against licence templates by the Dice coefficient over word bigrams, in SQL functions only.

A text is its sequence of word pairs.  A template is compared with every window of as many pairs that starts at one of its
own pairs, wherever it stands: on a line of its own, wrapped over lines, inside prose, or as the whole text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from detspark.llm import licence_texts

TEMPLATES = licence_texts.TEMPLATES
THRESHOLD = 0.8
_WORD = r"[\p{L}\p{N}]+(?:[.-][\p{L}\p{N}]+)*"


def words(text: Column) -> Column:
    """Lower-case words of letters, digits, dots and hyphens inside a word; everything else separates."""
    return F.regexp_extract_all(F.lower(text), F.lit(f"({_WORD})"), F.lit(1))


def _bound(value: Column, body) -> Column:
    """``body`` of a value that is computed once, as a lambda variable, and not again at each use."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def pairs(text: Column) -> Column:
    """Neighbouring words in order, repeats included; fewer than two words have none."""
    both = lambda w: F.zip_with(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, 2, F.greatest(F.size(w) - 1, F.lit(0))), lambda a, b: F.concat(a, F.lit(" "), b))
    return _bound(words(text), both)


def templates(spark, rows=TEMPLATES) -> DataFrame:
    """``(licence, t_grams, t_size, t_span)``: distinct pairs, their number, and the number of pairs with repeats.

    The table is a parameter and not data, so it may be broadcast.
    """
    table = spark.createDataFrame([(a, b) for a, b in rows], "licence string, notice string")
    spans = table.select("licence", F.explode(F.array(pairs(F.col("notice")))).alias("_p"))
    return spans.select("licence", F.array_distinct("_p").alias("t_grams"), F.size("_p").alias("t_span")).withColumn("t_size", F.size("t_grams")).where("t_size > 0")


def _windows() -> Column:
    """(start, dice) of the windows of ``_pairs`` that start at a place in ``_own`` and reach the threshold ``_t``."""

    def at(i: Column) -> Column:
        window = F.array_distinct(F.slice("_pairs", i + 1, F.col("t_span")))
        return _bound(window, lambda w: F.struct(i.alias("start"), (2.0 * F.size(F.array_intersect(w, F.col("t_grams"))) / (F.size(w) + F.col("t_size"))).alias("dice")))

    return F.filter(F.transform("_own", at), lambda w: w["dice"] >= F.col("_t") - 1e-9)


def _best(found: Column, span: Column) -> Column:
    """One window of every run of windows that overlap the one before: the highest coefficient, then the first."""
    empty = F.array().cast("array<struct<start:int,dice:double,last:int>>")

    def step(done: Column, w: Column) -> Column:
        held = F.get(done, F.size(done) - 1)
        joins = (F.size(done) > 0) & (w["start"] < held["last"] + span)
        better = w["dice"] > held["dice"]
        merged = F.struct(F.when(better, w["start"]).otherwise(held["start"]).alias("start"), F.greatest(w["dice"], held["dice"]).alias("dice"), w["start"].alias("last"))
        fresh = F.struct(w["start"].alias("start"), w["dice"].alias("dice"), w["start"].alias("last"))
        return F.when(joins, F.concat(F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0))), F.array(merged))).otherwise(F.concat(done, F.array(fresh)))

    return F.aggregate(found, empty, step)


def scan(docs: DataFrame, rows=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """``(doc_id, text)`` → ``(doc_id, line_no, licence, dice)``: where each template stands, by the line that the window begins on, from 1.

    Of windows that overlap, the best one is reported, the first of equals.  A coefficient of at least t needs t / (2 - t) of
    the template's pairs: so a text is dropped unless enough of its pairs belong to any template at all (a hashed look-up per
    pair), and then, for each template, unless enough distinct ones belong to it; only then windows are formed.  Null and
    empty texts and those of one word give no rows; repeated rows give repeated rows; other columns may have any name.
    """
    spark = docs.sparkSession
    table = templates(spark, rows)
    known = table.select("t_size", "t_grams").collect()  # a parameter, not data
    if not known:
        return docs.select("doc_id", F.lit(0).alias("line_no"), F.lit("").alias("licence"), F.lit(0.0).alias("dice")).where(F.lit(False))
    share = threshold / (2 - threshold)
    vocabulary = sorted({g for r in known for g in r["t_grams"]})
    least = min(-(-int(1e6 * (share * r["t_size"] - 1e-6)) // 10**6) for r in known)
    # an explode of one element keeps the optimiser from forming the pairs anew for each use
    paired = docs.where("text is not null").select("doc_id", "text", F.explode(F.array(pairs(F.col("text")))).alias("_pairs"))
    hits = F.filter(F.transform("_pairs", lambda g, i: F.when(g.isin(vocabulary), i)), lambda i: i.isNotNull())
    some = paired.withColumn("_hits", F.explode(F.array(hits))).where(F.size("_hits") >= max(least, 1))
    each = some.join(F.broadcast(table), F.size("_hits") >= F.lit(share) * F.col("t_size") - 1e-6)
    own = F.filter("_hits", lambda i: F.array_contains("t_grams", F.get("_pairs", i)))
    each = each.withColumn("_own", F.explode(F.array(own))).withColumn("_t", F.lit(threshold))
    enough = F.size(F.array_distinct(F.transform("_own", lambda i: F.get("_pairs", i)))) >= F.lit(share) * F.col("t_size") - 1e-6
    found = each.where(enough).withColumn("_found", F.explode(F.array(_windows()))).where(F.size("_found") > 0)
    placed = found.withColumn("_best", F.explode(_best(F.col("_found"), F.col("t_span")))).select("doc_id", "text", "licence", "_best")
    # words up to the end of each line; a line has begun where fewer words stand before it than before the window
    counts = F.transform(F.split("text", "\n"), lambda line: F.regexp_count(F.lower(line), F.lit(_WORD)))
    upto = F.aggregate(counts, F.array().cast("array<int>"), lambda done, n: F.concat(done, F.array(n + F.coalesce(F.get(done, F.size(done) - 1), F.lit(0)))))
    line = 1 + F.size(F.filter(upto, lambda n: n <= F.col("_best.start")))
    return placed.select("doc_id", line.alias("line_no"), "licence", F.col("_best.dice").alias("dice"))


def op8_licences(spark, sf_dir: str) -> DataFrame:
    """Licence texts and notices in ``documents``: one row for each place where a template stands, by document and line.

    Null, empty and one-word texts give no rows; rows that repeat give theirs again; an empty table gives no rows.
    """
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")).select("doc_id", F.col("line_no").cast("long").alias("line_no"), "licence", F.round("dice", 9).alias("dice"))


def _oracle() -> str:
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    notices = ", ".join(f"({quoted(a)}, {quoted(b)})" for a, b in TEMPLATES)
    tokens = lambda c: f"regexp_extract_all(lower({c}), '{_WORD}')"
    grams = "list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])"
    return f"""
WITH t AS (SELECT licence, list_distinct(p) AS g, len(p) AS span FROM (SELECT licence, {grams} AS p FROM (SELECT licence, {tokens('notice')} AS w FROM (VALUES {notices}) v(licence, notice))) WHERE len(p) > 0),
d AS (SELECT r, doc_id, text, {grams} AS p FROM (SELECT row_number() OVER () AS r, doc_id, text, {tokens('text')} AS w FROM documents WHERE text IS NOT NULL) WHERE len(w) > 1),
places AS (SELECT r, unnest(p) AS gram, unnest(range(0, len(p))) AS i FROM d),
own AS (SELECT licence, unnest(g) AS gram FROM t),
many AS (SELECT r, licence FROM places JOIN own USING (gram) GROUP BY r, licence HAVING count(DISTINCT gram) >= (SELECT len(g) FROM t WHERE t.licence = own.licence) * {THRESHOLD} / (2 - {THRESHOLD}) - 1e-6),
windows AS (SELECT r, licence, i, span, g, list_distinct(p[i + 1:i + span]) AS x FROM many JOIN places USING (r) JOIN own USING (licence, gram) JOIN t USING (licence) JOIN d USING (r)),
scored AS (SELECT r, licence, i, span, 2.0 * len(list_intersect(x, g)) / (len(x) + len(g)) AS dice FROM windows),
good AS (SELECT *, coalesce((i >= lag(i) OVER w + span)::INT, 0) AS cut FROM scored WHERE dice >= {THRESHOLD} - 1e-9 WINDOW w AS (PARTITION BY r, licence ORDER BY i)),
runs AS (SELECT *, sum(cut) OVER (PARTITION BY r, licence ORDER BY i) AS run FROM good),
best AS (SELECT * FROM runs QUALIFY row_number() OVER (PARTITION BY r, licence, run ORDER BY dice DESC, i) = 1),
lines AS (SELECT r, sum(n) OVER (PARTITION BY r ORDER BY k) AS upto FROM (SELECT r, unnest(range(0, len(l))) AS k, unnest(list_transform(l, lambda x: len({tokens('x')}))) AS n FROM (SELECT r, string_split(text, chr(10)) AS l FROM d WHERE r IN (SELECT r FROM best))))
SELECT d.doc_id, 1 + (SELECT count(*) FROM lines WHERE lines.r = best.r AND lines.upto <= best.i) AS line_no, best.licence, round(best.dice::DOUBLE, 9) AS dice FROM best JOIN d USING (r)
"""


ORACLE = _oracle()
