"""Sources and sinks: the given tables, configuration sets made from them, files of bit strings, staged tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from detspark.functions import bits
from detspark.functions.schema import ProblemSpec, require

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")

#: size of each set: orbitals and occupied
SETS = {
    "emb12": ProblemSpec(12, 4), "emb16": ProblemSpec(16, 4), "emb20": ProblemSpec(20, 5), "emb64": ProblemSpec(64, 6),
    "ord3": ProblemSpec(25, 3), "ord4": ProblemSpec(25, 4), "evt3": ProblemSpec(24, 3), "doc6": ProblemSpec(26, 6),
}

EVENTS = T.StructType(
    [T.StructField("event_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("user_id", T.LongType()), T.StructField("event_type", T.StringType()), T.StructField("value", T.DoubleType()), T.StructField("props", T.StringType())]
)


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_positions(frame: DataFrame, positions: str, spec: ProblemSpec) -> DataFrame:
    """Distinct configurations of a column of orbital arrays; rows without exactly ``n`` distinct orbitals go."""
    good = frame.where(F.size(F.array_distinct(positions)) == spec.n)
    return good.select(*[w.alias(c) for w, c in zip(bits.pack(F.col(positions), spec.m), spec.names, strict=True)]).distinct()


def top_coordinates(embeddings: DataFrame, spec: ProblemSpec) -> DataFrame:
    """The ``n`` largest of the first ``m`` coordinates, ties to the lower one."""
    pairs = F.transform(F.slice("embedding", 1, spec.m), lambda x, i: F.struct((-x).alias("v"), i.alias("i")))
    ranked = F.slice(F.array_sort(pairs), 1, spec.n)
    return from_positions(embeddings.select(F.transform(ranked, lambda s: s["i"]).alias("at")), "at", spec)


def brand_ranks(part: DataFrame) -> DataFrame:
    """``(p_partkey, o)``: rank of the part's brand among the brands, from 0.  There are a few dozen brands."""
    brands = part.select("p_brand").distinct().withColumn("o", F.dense_rank().over(Window.orderBy("p_brand")) - 1)
    return part.join(F.broadcast(brands), "p_brand").select("p_partkey", "o")


def baskets(lineitem: DataFrame, part: DataFrame, spec: ProblemSpec) -> DataFrame:
    """Per order its ``n`` lowest distinct brand ranks; orders with fewer go.  The line table is shuffled once, by order, after a partial aggregate."""
    lines = lineitem.select("l_orderkey", "l_partkey").join(brand_ranks(part), F.col("l_partkey") == F.col("p_partkey"))
    per_order = lines.groupBy("l_orderkey").agg(F.sort_array(F.collect_set("o")).alias("all"))
    return from_positions(per_order.select(F.slice("all", 1, spec.n).alias("at")), "at", spec)


def busy_hours(events: DataFrame, spec: ProblemSpec) -> DataFrame:
    """Per user and day the ``n`` hours with most events, ties to the lower hour."""
    hourly = events.groupBy("user_id", F.to_date("ts").alias("day"), F.hour("ts").alias("hour")).agg(F.count("*").alias("c"))
    daily = hourly.groupBy("user_id", "day").agg(F.array_sort(F.collect_list(F.struct((-F.col("c")).alias("c"), "hour"))).alias("all"))
    return from_positions(daily.select(F.transform(F.slice("all", 1, spec.n), lambda s: s["hour"]).alias("at")), "at", spec)


def letters(documents: DataFrame, spec: ProblemSpec) -> DataFrame:
    """Per document its ``n`` most frequent letters a to z, ties to the lower letter; only letters that occur count."""
    text = F.lower("text")
    counts = F.transform(F.sequence(F.lit(0), F.lit(25)), lambda i: F.struct((-(F.length(text) - F.length(F.replace(text, F.char(i + 97))))).alias("c"), i.cast("int").alias("i")))
    best = F.slice(F.array_sort(F.filter(counts, lambda s: s["c"] < 0)), 1, spec.n)
    return from_positions(documents.where("text is not null").select(F.transform(best, lambda s: s["i"]).alias("at")), "at", spec)


def configuration_set(spark: SparkSession, sf_dir: str, name: str) -> tuple[ProblemSpec, DataFrame]:
    """One of the named sets of ``SETS``, as distinct rows of word columns."""
    spec = SETS[name]
    table = lambda t: load(spark, sf_dir, t)
    if name.startswith("emb"):
        return spec, top_coordinates(table("embeddings"), spec)
    if name.startswith("ord"):
        return spec, baskets(table("lineitem"), table("part"), spec)
    if name == "evt3":
        return spec, busy_hours(table("events"), spec)
    return spec, letters(table("documents"), spec)


def line_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dense integer keys for de-duplication only: part and supplier of each line in one word."""
    return load(spark, sf_dir, "lineitem").select((F.col("l_partkey") * (1 << 20) + F.col("l_suppkey")).alias("w0"))


def read_bitstrings(spark: SparkSession, path: str, spec: ProblemSpec, fmt: str = "csv", column: str = "bits") -> DataFrame:
    """Configurations from files of bit strings (csv with a header, json or orc)."""
    reader = spark.read.schema(f"{column} string")
    frame = {"csv": lambda: reader.option("header", True).csv(path), "json": lambda: reader.json(path), "orc": lambda: reader.orc(path)}[fmt]()
    return frame.select(*[w.alias(c) for w, c in zip(bits.parse(F.col(column), spec.m), spec.names, strict=True)])


def read_integrals(spark: SparkSession, path: str) -> DataFrame:
    """``(v, p, q, r, s)`` from lines of a value and four orbital numbers from 1 (0: unused); other lines are skipped."""
    number = r"^\s*([-+0-9.eEdD]+)\s+(\d+)\s+(\d+)\s+(\d+)\s+(\d+)\s*$"
    lines = spark.read.text(path).where(F.col("value").rlike(number))
    pick = lambda i: F.regexp_extract("value", number, i)
    return lines.select(F.translate(pick(1), "dD", "eE").cast("double").alias("v"), *[pick(i + 2).cast("int").alias(c) for i, c in enumerate("pqrs")])


def write_sorted(frame: DataFrame, path: str, spec: ProblemSpec, partitions: int | None = None, by: list[str] | None = None) -> None:
    """Staged table in key order: file statistics then act as an index on the key."""
    require(frame, spec.names)
    order = [F.col(c) for c in spec.order]
    laid = frame.repartitionByRange(partitions, *order) if partitions else frame
    writer = laid.sortWithinPartitions(*order).write.mode("overwrite")
    (writer.partitionBy(*by) if by else writer).parquet(path)


def stream_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def stream_rate(spark: SparkSession, rows_per_second: int = 100) -> DataFrame:
    """Synthetic keys for tests of streaming sinks."""
    return spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load().select(F.col("value").alias("w0"), "timestamp")
