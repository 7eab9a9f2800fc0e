"""Point sets on the given tables, as integer 2-D grids or double vectors; checks and scaling.

Each recipe is one projection of its table, written once for two SQL dialects: the queries run it in Spark, the
oracles in DuckDB.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from densereps.functions.expr import cell

POINTS_2D = "id long, x long, y long, truth int"


def _draw(i: str, mult: int, shift: str, scale: int, dialect: str) -> str:
    """A congruential draw below scale from the integer i."""
    return _div(f"(({i} * {mult} + {shift}) % 1000003) * {scale}", "1000003", dialect)


def _div(a: str, b: str, dialect: str) -> str:
    return f"(({a}) div ({b}))" if dialect == "spark" else f"(({a}) // ({b}))"


def _hex(at: int, n: int, dialect: str) -> str:
    return f"CAST(conv(substr(h, {at}, {n}), 16, 10) AS BIGINT)" if dialect == "spark" else f"CAST('0x' || substr(h, {at}, {n}) AS BIGINT)"


def _family(f: str, a: str, b: str, core: tuple[str, str] | None, dialect: str) -> tuple[str, str]:
    """x and y of a shape: 0 block, 1 hollow square, then a core block if given, last an L."""
    d = lambda x, y: _div(x, str(y), dialect)
    side, w = d(f"{b} * 4", 1000), d(f"({b} * 4) % 1000", 10)
    frame_x = f"CASE {side} WHEN 0 THEN {a} WHEN 1 THEN {a} WHEN 2 THEN {w} ELSE 1000 - {w} END"
    frame_y = f"CASE {side} WHEN 0 THEN {w} WHEN 1 THEN 1000 - {w} ELSE {a} END"
    ell_x = f"CASE WHEN {b} < 500 THEN {a} ELSE {d(f'{b} - 500', 5)} END"
    ell_y = f"CASE WHEN {b} < 500 THEN {d(b, 5)} ELSE {a} END"
    mid = (f"WHEN 2 THEN {core[0]}", f"WHEN 2 THEN {core[1]}") if core else ("", "")
    return (
        f"CASE {f} WHEN 0 THEN {a} WHEN 1 THEN {frame_x} {mid[0]} ELSE {ell_x} END",
        f"CASE {f} WHEN 0 THEN {d(b, 2)} WHEN 1 THEN {frame_y} {mid[1]} ELSE {ell_y} END",
    )


def _shapes9(table: str, key: str, dialect: str) -> str:
    d = lambda x, y: _div(x, str(y), dialect)
    x, y = _family("s % 3", "a", "b", None, dialect)
    a, b = _draw("i", 618034, "0", 1000, dialect), _draw("i", 754878, "s * 7919", 1000, dialect)
    return (
        f"SELECT id, 2000 * (s % 3) + ({x}) AS x, 2000 * {d('s', 3)} + ({y}) AS y, CAST(s AS INT) AS truth FROM "
        f"(SELECT id, s, {a} AS a, {b} AS b FROM (SELECT CAST({key} AS BIGINT) AS id, CAST({key} % 9 AS BIGINT) AS s, "
        f"CAST({d(key, 9)} AS BIGINT) AS i FROM {table}))"
    )


def _shapes41(dialect: str) -> str:
    d = lambda x, y: _div(x, str(y), dialect)
    key = "concat_ws('|', CAST(l_orderkey AS STRING), CAST(l_linenumber AS STRING), CAST(l_partkey AS STRING), CAST(l_suppkey AS STRING))"
    x, y = _family("s % 4", "a", "b", (f"400 + {d('a', 5)}", f"400 + {d('b', 5)}"), dialect)
    tile = "CASE WHEN s % 4 = 2 AND s % 7 > 0 THEN s - 1 ELSE s END"
    text = f"SELECT DISTINCT md5({key}) AS h FROM lineitem"
    return (
        f"SELECT id, CASE WHEN r % 100 < 2 THEN 12 * a + r % 12 WHEN r % 100 = 2 THEN 800 + {d('3 * a', 2)} ELSE 1700 * (t % 7) + ({x}) END AS x, "
        f"CASE WHEN r % 100 < 2 THEN 10 * b WHEN r % 100 = 2 THEN 300 + {d('b', 25)} ELSE 1700 * {d('t', 7)} + ({y}) END AS y, "
        f"CAST(CASE WHEN r % 100 < 2 THEN -1 WHEN r % 100 = 2 THEN -2 ELSE s END AS INT) AS truth FROM "
        f"(SELECT *, {tile} AS t FROM (SELECT {_hex(1, 15, dialect)} AS id, {_hex(16, 5, dialect)} AS r, "
        f"{d(_hex(21, 6, dialect) + ' * 1000', 16777216)} AS a, {d(_hex(27, 6, dialect) + ' * 1000', 16777216)} AS b, "
        f"{d(_hex(16, 5, dialect), 100)} % 41 AS s FROM ({text if dialect == 'spark' else text.replace('STRING', 'VARCHAR')})))"
    )


#: Multipliers of the four draws of each coordinate of the blobs. Fixed values.
BLOB_X, BLOB_Y = (618034, 754878, 569841, 324718), (414214, 732051, 236068, 645751)


def _blobs(k: int, pitch: int, dialect: str) -> str:
    total = lambda ms, step: " + ".join(_draw("i", m, f"s * {step}", 250, dialect) for m in ms)
    return (
        f"SELECT id, {pitch} * (s % 6) + {total(BLOB_X, 7919)} AS x, {pitch} * {_div('s', '6', dialect)} + {total(BLOB_Y, 104729)} AS y, CAST(s AS INT) AS truth "
        f"FROM (SELECT CAST(p_partkey AS BIGINT) AS id, CAST(p_partkey % {k} AS BIGINT) AS s, CAST({_div('p_partkey', str(k), dialect)} AS BIGINT) AS i FROM part)"
    )


def _events(dialect: str) -> str:
    minutes = (
        "CAST(timestampdiff(MINUTE, TIMESTAMP_NTZ'2024-01-01 00:00:00', CAST(ts AS TIMESTAMP_NTZ)) AS BIGINT)"
        if dialect == "spark"
        else "CAST((epoch_us(ts) // 1000000 - 1704067200) // 60 AS BIGINT)"
    )
    return f"SELECT event_id AS id, {minutes} AS x, CAST(round(100 * value) AS BIGINT) AS y, CAST(NULL AS INT) AS truth FROM events"


def recipe(name: str, dialect: str = "spark") -> str:
    """SELECT id, x, y, truth of a 2-D point set."""
    return {
        "shapes9_small": lambda: _shapes9("customer", "c_custkey", dialect),
        "shapes9_large": lambda: _shapes9("orders", "o_orderkey", dialect),
        "shapes41_noise": lambda: _shapes41(dialect),
        "blobs30": lambda: _blobs(30, 1200, dialect),
        "blobs31": lambda: _blobs(31, 650, dialect),
        "part_grid": lambda: "SELECT CAST(p_partkey AS BIGINT) AS id, CAST(100 * p_size AS BIGINT) AS x, CAST(round(100 * p_retailprice) AS BIGINT) AS y, CAST(NULL AS INT) AS truth FROM part",
        "events_xy": lambda: _events(dialect),
    }[name]()


TABLE_OF = {
    "shapes9_small": "customer", "shapes9_large": "orders", "shapes41_noise": "lineitem", "blobs30": "part", "blobs31": "part",
    "part_grid": "part", "events_xy": "events",
}


def load_points(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A 2-D point set by name: (id, x, y, truth)."""
    table = TABLE_OF[name]
    held = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    text = recipe(name).replace(f"FROM {table}", "FROM {held}")
    return spark.sql(text, held=held).select("id", F.col("x").cast("long"), F.col("y").cast("long"), "truth")


def read_points(spark: SparkSession, path: str, kind: str, schema: str = POINTS_2D) -> DataFrame:
    """Points from files of a kind that Spark reads, with a stated schema, so that no pass infers one."""
    return spark.read.schema(schema).option("header", True).format(kind).load(path)


def write_points(df: DataFrame, table: str, buckets: int, side: float) -> None:
    """Points as a table bucketed by cell, so that joins on cells of that side need no shuffle."""
    cells = df.withColumn("cx", cell("x", side)).withColumn("cy", cell("y", side))
    cells.write.bucketBy(buckets, "cx", "cy").sortBy("cx", "cy").mode("overwrite").saveAsTable(table)


def load_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The high-dimensional set: (id, vec, truth)."""
    held = spark.read.parquet(f"{sf_dir}/embeddings.parquet")
    return held.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"), F.col("label").alias("truth"))


def load_documents(spark: SparkSession, sf_dir: str, truth: str = "lang") -> DataFrame:
    """Documents by (per mille of non-ASCII characters times ten, mean word length times 100)."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    odd = F.length(F.regexp_replace("text", r"[ -~\n]", ""))
    n_words = F.size(F.split("text", r"\s+"))
    rows = docs.select(
        F.col("doc_id").alias("id"), F.floor(F.lit(10_000) * odd / F.greatest(F.length("text"), F.lit(1))).cast("long").alias("x"),
        F.floor(F.lit(100) * F.length("text") / n_words).cast("long").alias("y"), "lang",
    )
    if truth == "lang":
        return rows.withColumnRenamed("lang", "truth")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select(F.col("doc_id").alias("id"), F.col(truth).alias("truth"))
    return rows.drop("lang").join(labels, "id", "left")


def to_vec(df: DataFrame, columns: list[str], into: str = "vec") -> DataFrame:
    return df.withColumn(into, F.array(*[F.col(c).cast("double") for c in columns]))


def validate_points(df: DataFrame, columns: list[str]) -> DataFrame:
    """One row: n, and how many have a null, a NaN or an infinite coordinate."""
    values = [F.col(c).cast("double") for c in columns]

    def some(test) -> Column:
        found = F.lit(False)
        for v in values:
            found = found | F.coalesce(test(v), F.lit(False))
        return F.sum(found.cast("long"))

    return df.agg(
        F.count(F.lit(1)).alias("n"), F.coalesce(some(lambda v: v.isNull()), F.lit(0)).alias("n_null"),
        F.coalesce(some(F.isnan), F.lit(0)).alias("n_nan"), F.coalesce(some(lambda v: F.abs(v) == F.lit(float("inf"))), F.lit(0)).alias("n_infinite"),
    )


def finite(df: DataFrame, columns: list[str]) -> DataFrame:
    """The rows with finite coordinates."""
    for c in columns:
        v = F.col(c).cast("double")
        df = df.filter(v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return df


def scale(df: DataFrame, columns: list[str], how: str = "minmax") -> DataFrame:
    """Columns scaled to 0..1, or to mean 0 and sample deviation 1, by one aggregate row."""
    first, second = (F.min, F.max) if how == "minmax" else (F.avg, F.stddev_samp)
    row = df.agg(*[first(c).alias(f"a{i}") for i, c in enumerate(columns)], *[second(c).alias(f"b{i}") for i, c in enumerate(columns)]).first()
    for i, c in enumerate(columns):
        low = row[f"a{i}"]
        width = (row[f"b{i}"] - low) if how == "minmax" else row[f"b{i}"]
        df = df.withColumn(c, (F.col(c) - F.lit(low)) / F.lit(width if width else 1.0))
    return df
