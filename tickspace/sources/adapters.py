"""The given tables as agent extents: typed projections, no inference."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.exact import noise


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_stream(spark: SparkSession, sf_dir: str, name: str, files: int = 1) -> DataFrame:
    """A table as a stream, ``files`` files a batch; by a pattern, as a file
    source takes the name of a single file for a folder's."""
    schema = read(spark, sf_dir, name).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{sf_dir}/{name}.parque[t]")


def cents(col: str):
    return F.floor(F.col(col) * 100 + 0.5).cast("bigint")


def fish_rows(events: DataFrame) -> DataFrame:
    """events, static or streaming: x along time, y along value (skewed),
    speeds from the user."""
    micros = F.timestamp_diff("MICROSECOND", F.lit("2024-01-01").cast("timestamp_ntz"), F.col("ts"))
    return events.select(
        F.col("event_id").cast("bigint").alias("id"),
        F.floor(micros / F.lit(26_000_000)).cast("bigint").alias("x"),
        cents("value").alias("y"),
        (F.col("user_id") % 21 - 10).cast("bigint").alias("vx"),
        (F.col("user_id") % 17 - 8).cast("bigint").alias("vy"),
        (F.col("user_id") % 20).cast("bigint").alias("informed"),
    )


def fish_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fish_rows(read(spark, sf_dir, "events"))


def fish_stream(spark: SparkSession, sf_dir: str, files: int = 1) -> DataFrame:
    """The same agents as they arrive, ``files`` files a batch."""
    return fish_rows(read_stream(spark, sf_dir, "events", files))


def vehicle_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """orders: the segment's length grows with the number of vehicles."""
    orders = read(spark, sf_dir, "orders")
    n = orders.agg(F.count("*").alias("n"))
    pos = F.floor((cents("o_totalprice") - 100_000) * 120 * F.col("n") / F.lit(49_900_000)).cast("bigint")
    return orders.join(F.broadcast(n)).select(  # one row
        F.col("o_orderkey").cast("bigint").alias("id"),
        (F.substring("o_orderpriority", 1, 1).cast("bigint") - 1).alias("lane"),
        pos.alias("pos"),
        (200 + F.col("o_custkey") % 130).cast("bigint").alias("v"),
        (200 + F.col("o_custkey") % 130).cast("bigint").alias("desired"),
    )


def prey_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "customer").select(F.col("c_custkey").cast("bigint").alias("id"), (cents("c_acctbal") + 100_000).alias("x"), (F.col("c_custkey") * 7919 % 1_000_003).cast("bigint").alias("y"), F.lit(100).cast("bigint").alias("energy"))


def predator_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("bigint").alias("id"), (cents("s_acctbal") + 100_000).alias("x"), (F.col("s_suppkey") * 104_729 % 1_000_003).cast("bigint").alias("y"), F.lit(100).cast("bigint").alias("energy"))


def vec_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = [F.floor(F.col("embedding")[i].cast("double") * 1_000_000).cast("bigint").alias(f"e{i + 1}") for i in range(3)]
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("id"), *e, F.col("label").cast("bigint").alias("label"))


def lattice_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "part").select(F.col("p_partkey").cast("bigint").alias("id"), F.col("p_size").cast("bigint").alias("x"), F.floor(F.col("p_retailprice") * 10 + 0.5).cast("bigint").alias("y"), F.col("p_brand").alias("brand"))


def doc_agents(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = read(spark, sf_dir, "labels").select("doc_id", "quality", "toxic")
    return read(spark, sf_dir, "documents").select("doc_id", "n_chars", "lang", "source").join(labels, "doc_id", "left").select(F.col("doc_id").alias("id"), F.col("n_chars").alias("x"), "lang", "source", "quality", "toxic")


def scenario(spark: SparkSession, path: str, columns: list[str], fmt: str = "csv") -> DataFrame:
    """An extent from CSV files with a header, or JSON lines: the class's
    columns, all integers.  No type is inferred; a value of another type fails
    the read.  CSV names and their order must match; a name missing in a JSON
    line is null, one too many there is left out."""
    if fmt not in ("csv", "json"):
        raise ValueError(f"scenario files are csv or json, not {fmt}")
    named = {"header": "true", "enforceSchema": "false"} if fmt == "csv" else {}
    return spark.read.format(fmt).schema(", ".join(f"{c} bigint" for c in columns)).options(mode="FAILFAST", **named).load(path)


def synthetic(spark: SparkSession, n: int, spans: dict[str, tuple[int, int]], seed: int = 7, parts: int | None = None) -> DataFrame:
    """``n`` agents with ids from 0, each column drawn from its span (low, high
    exclusive).  A draw depends on id, column and seed only, so the extent is the
    same for any number of parts, and nothing is held or moved to make it."""
    for c, (low, high) in spans.items():
        if high <= low:
            raise ValueError(f"empty span of {c}: {low}, {high}")
    draws = [F.expr(f"CAST({low} + ({noise('id', 0, i, seed)}) % {high - low} AS BIGINT)").alias(c) for i, (c, (low, high)) in enumerate(spans.items())]
    return spark.range(0, n, 1, parts).select("id", *draws)


def save_bucketed(agents: DataFrame, name: str, by: str = "id", buckets: int = 64, path: str | None = None) -> DataFrame:
    """``agents`` as a table of the catalogue, dealt and sorted by ``by``: joins
    and groups by it with tables of as many buckets need no exchange."""
    dealt = agents.repartition(buckets, by).write.mode("overwrite").format("parquet").bucketBy(buckets, by).sortBy(by)
    (dealt.option("path", path) if path else dealt).saveAsTable(name)
    return agents.sparkSession.table(name)


#: the same projections for DuckDB, written by hand
ORACLE = {
    "fish": "SELECT CAST(event_id AS BIGINT) AS id, CAST(floor(date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 26000000.0::DOUBLE) AS BIGINT) AS x, CAST(floor(value * 100 + 0.5::DOUBLE) AS BIGINT) AS y, CAST(user_id % 21 - 10 AS BIGINT) AS vx, CAST(user_id % 17 - 8 AS BIGINT) AS vy, CAST(user_id % 20 AS BIGINT) AS informed FROM events",
    "vehicle": "SELECT CAST(o_orderkey AS BIGINT) AS id, CAST(substr(o_orderpriority, 1, 1) AS BIGINT) - 1 AS lane, CAST(floor(CAST((CAST(floor(o_totalprice * 100 + 0.5::DOUBLE) AS BIGINT) - 100000) * 120 * (SELECT count(*) FROM orders) AS DOUBLE) / 49900000) AS BIGINT) AS pos, CAST(200 + o_custkey % 130 AS BIGINT) AS v, CAST(200 + o_custkey % 130 AS BIGINT) AS desired FROM orders",
    "prey": "SELECT CAST(c_custkey AS BIGINT) AS id, CAST(floor(c_acctbal * 100 + 0.5::DOUBLE) AS BIGINT) + 100000 AS x, CAST(c_custkey * 7919 % 1000003 AS BIGINT) AS y, CAST(100 AS BIGINT) AS energy FROM customer",
    "predator": "SELECT CAST(s_suppkey AS BIGINT) AS id, CAST(floor(s_acctbal * 100 + 0.5::DOUBLE) AS BIGINT) + 100000 AS x, CAST(s_suppkey * 104729 % 1000003 AS BIGINT) AS y, CAST(100 AS BIGINT) AS energy FROM supplier",
    "vec": "SELECT CAST(vec_id AS BIGINT) AS id, CAST(floor(CAST(embedding[1] AS DOUBLE) * 1000000) AS BIGINT) AS e1, CAST(floor(CAST(embedding[2] AS DOUBLE) * 1000000) AS BIGINT) AS e2, CAST(floor(CAST(embedding[3] AS DOUBLE) * 1000000) AS BIGINT) AS e3, CAST(label AS BIGINT) AS label FROM embeddings",
    "lattice": "SELECT CAST(p_partkey AS BIGINT) AS id, CAST(p_size AS BIGINT) AS x, CAST(floor(p_retailprice * 10 + 0.5::DOUBLE) AS BIGINT) AS y, p_brand AS brand FROM part",
    "doc": "SELECT d.doc_id AS id, n_chars AS x, lang, source, quality, toxic FROM documents d LEFT JOIN labels USING (doc_id)",
}
EXTENTS = {"fish": fish_agents, "vehicle": vehicle_agents, "prey": prey_agents, "predator": predator_agents, "vec": vec_agents, "lattice": lattice_agents, "doc": doc_agents}
