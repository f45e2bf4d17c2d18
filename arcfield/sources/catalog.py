"""Sky views: positions derived from the given tables, alike in Spark and SQL.

The tables hold no coordinates.  Right ascension is integer arithmetic on the
key; z is linear in a value column, which spreads objects evenly by area.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# name: (table, id, z, other columns as (name, expression)); expressions hold in Spark SQL and DuckDB
VIEWS = {
    "sky_orders": ("orders", "o_orderkey", "o_totalprice / 250000.0e0 - 1", (("epoch", "o_orderdate"), ("class", "o_orderpriority"), ("magnitude", "o_totalprice"))),
    "sky_customer": ("customer", "c_custkey", "(c_acctbal + 1000) / 5500.0e0 - 1", (("class", "c_mktsegment"), ("nationkey", "c_nationkey"))),
    "sky_supplier": ("supplier", "s_suppkey", "(s_acctbal + 1000) / 5500.0e0 - 1", (("nationkey", "s_nationkey"),)),
    "sky_part": ("part", "p_partkey", "(p_retailprice - 900) / 50.0e0 - 1", (("radius", "0.02e0 * power(2.0e0, p_size % 10)"), ("brand", "p_brand"))),
    "sky_lineitem": ("(SELECT l_orderkey * 8 + l_linenumber AS k, min(l_extendedprice) AS price, min(l_quantity) AS quantity FROM lineitem GROUP BY l_orderkey * 8 + l_linenumber) AS grouped", "k", "price / 52500.0e0 - 1", (("price", "price"), ("quantity", "quantity"))),
    "sky_events": ("events", "event_id", "greatest(-1.0e0, least(1.0e0, 2 * ((user_id * 7919) % 1000 + 0.5e0) / 1000 - 1 + value / 100000.0e0))", (("ts", "ts"), ("event_type", "event_type"), ("value", "value"), ("props", "props"), ("user_id", "user_id"))),
}
RA_OF = {"sky_events": "user_id"}


def inner_sql(name: str, quote: str = '"') -> str:
    """SELECT of obj_id, ra, z and the other columns."""
    source, key, z, other = VIEWS[name]
    q = lambda c: f"{quote}{c}{quote}"
    extra = "".join(f", {q(e) if e == n else e} AS {q(n)}" for n, e in other)
    ra = RA_OF.get(name, key)
    return f"SELECT CAST({key} AS BIGINT) AS obj_id, ((CAST({ra} AS BIGINT) * 137507764) % 360000000) / 1000000.0e0 AS ra, {z} AS z{extra} FROM {source}"


def view_sql(name: str) -> str:
    """The view as DuckDB SQL."""
    other = "".join(f', "{n}"' for n, _ in VIEWS[name][3])
    return f'SELECT obj_id, ra, degrees(asin(z)) AS "dec", sqrt(1 - z * z) * cos(radians(ra)) AS x, sqrt(1 - z * z) * sin(radians(ra)) AS y, z{other} FROM ({inner_sql(name)}) AS placed'


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sky(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A view of VIEWS; objects with a null or NaN coordinate are left out (see ``rejects``)."""
    source, key, z, other = VIEWS[name]
    if name == "sky_lineitem":
        raw = table(spark, sf_dir, "lineitem").groupBy((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("k")).agg(F.min("l_extendedprice").alias("price"), F.min("l_quantity").alias("quantity"))
    else:
        raw = table(spark, sf_dir, source)
    ra = F.expr(f"((CAST({RA_OF.get(name, key)} AS BIGINT) * 137507764) % 360000000) / 1000000.0e0")
    placed = raw.select(F.expr(f"CAST({key} AS BIGINT)").alias("obj_id"), ra.alias("ra"), F.expr(z).alias("z"), *[F.expr(e).alias(n) for n, e in other])
    return positions(placed).where(usable())


def positions(df: DataFrame) -> DataFrame:
    """Add dec, x and y to rows with ra and z."""
    flat = F.sqrt(1 - F.col("z") * F.col("z"))
    other = [c for c in df.columns if c not in ("obj_id", "ra", "z")]
    return df.select("obj_id", "ra", F.degrees(F.asin("z")).alias("dec"), (flat * F.cos(F.radians("ra"))).alias("x"), (flat * F.sin(F.radians("ra"))).alias("y"), "z", *other)


def usable():
    """A position that an index can hold."""
    fine = F.lit(True)
    for c in ("ra", "dec", "x", "y", "z"):
        fine = fine & F.col(c).isNotNull() & ~F.isnan(c)
    return fine


def rejects(df: DataFrame) -> DataFrame:
    return df.where(~F.coalesce(usable(), F.lit(False)))


def sky_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First three components of the embeddings, on the unit sphere."""
    v = [F.get("embedding", F.lit(k)).cast("double") for k in range(3)]
    norm = F.sqrt(v[0] * v[0] + v[1] * v[1] + v[2] * v[2])
    flat = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("obj_id"), *[(c / norm).alias(k) for k, c in zip("xyz", v)], "label", "embedding")
    ra = F.degrees(F.atan2("y", "x"))
    return flat.select("obj_id", F.when(ra < 0, ra + 360).otherwise(ra).alias("ra"), F.degrees(F.asin("z")).alias("dec"), "x", "y", "z", "label", "embedding").where(usable())


def footprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One patch a nation: a ra band of 72 degrees and a z band of 0.4."""
    n = table(spark, sf_dir, "nation")
    k = F.col("n_nationkey")
    low, z = 72.0 * F.floor(k / 5), 0.4 * (k % 5) - 1
    return n.select(k.alias("nationkey"), F.col("n_regionkey").alias("regionkey"), low.cast("double").alias("ra_lo"), (low + 72.0).cast("double").alias("ra_hi"), z.alias("z_lo"), (z + 0.4).alias("z_hi"))


FOOTPRINTS_SQL = "SELECT n_nationkey AS nationkey, n_regionkey AS regionkey, 72.0e0 * (n_nationkey // 5) AS ra_lo, 72.0e0 * (n_nationkey // 5) + 72.0e0 AS ra_hi, 0.4e0 * (n_nationkey % 5) - 1 AS z_lo, 0.4e0 * (n_nationkey % 5) - 1 + 0.4e0 AS z_hi FROM nation"
