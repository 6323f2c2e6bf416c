"""Vector views over the given tables, and the hygiene that graphs need.

A view has ``vec_id long, embedding array<double>``; extra columns may follow.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from annspark.plans.skew import join_hot_apart
from annspark.sources.tables import table

HASH_DIM = 128


def standardised(df: DataFrame, id_column: Column, columns: dict[str, Column]) -> DataFrame:
    """Each column less its mean, over its sample deviation: one small aggregate, then a projection."""
    values = df.select(id_column.cast("long").alias("vec_id"), *[(c.cast("double") + 0.0).alias(n) for n, c in columns.items()])
    stats = values.agg(*[f(n).alias(f"{n}_{k}") for n in columns for k, f in (("mean", F.avg), ("dev", F.stddev_samp))]).first()
    parts = []
    for n in columns:
        mean, dev = stats[f"{n}_mean"], stats[f"{n}_dev"]
        parts.append((F.col(n) - F.lit(mean)) / F.lit(dev) if dev else F.lit(0.0))
    return values.select("vec_id", F.array(*parts).alias("embedding"))


def v_emb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("long"), F.col("embedding").cast("array<double>"), "label")


def v_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem")
    # Order and line number repeat here; 60 bits of a hash of the four keys tell rows apart, in other SQL engines too.
    keys = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    ident = F.conv(F.substring(F.md5(keys.cast("binary")), 1, 15), 16, 10).cast("long")
    return standardised(line, ident, {c: F.col(f"l_{c}") for c in ("quantity", "extendedprice", "discount", "tax")})


def v_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    return standardised(table(spark, sf_dir, "events"), F.col("event_id"), {"value": F.col("value"), "second": F.pmod(seconds, F.lit(86400.0)), "epoch": seconds})


def v_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return standardised(table(spark, sf_dir, "part"), F.col("p_partkey"), {"size": F.col("p_size"), "price": F.col("p_retailprice")})


def v_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    epoch = F.unix_micros(F.col("o_orderdate").cast("timestamp")) / 1e6
    return standardised(table(spark, sf_dir, "orders"), F.col("o_orderkey"), {"price": F.col("o_totalprice"), "epoch": epoch})


def _with_region(spark: SparkSession, sf_dir: str, name: str, key: str, nation: str, balance: str) -> DataFrame:
    """Standardised balance beside the region as five 0/1 components; nation and region are tables of fixed size."""
    rows = table(spark, sf_dir, name)
    regions = table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias(nation), F.col("n_regionkey"))
    scaled = standardised(rows, F.col(key), {"balance": F.col(balance)})
    place = rows.join(F.broadcast(regions), nation).select(F.col(key).cast("long").alias("vec_id"), "n_regionkey")
    hot = F.array(*[F.when(F.col("n_regionkey") == r, 1.0).otherwise(0.0) for r in range(5)])
    return scaled.join(place, "vec_id").select("vec_id", F.concat("embedding", hot).alias("embedding"))


def v_cust(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _with_region(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal")


def v_supp(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _with_region(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey", "s_acctbal")


def hashed_text(df: DataFrame, ident: Column, text: Column, dim: int = HASH_DIM) -> DataFrame:
    """Signed hashing of lower-case words into ``dim`` buckets, unit length; texts without words have no row.

    md5 rather than a Spark-only hash, so that other SQL engines agree.
    """
    words = df.select(ident.cast("long").alias("vec_id"), F.explode(F.split(F.lower(text), r"[\x20\x09-\x0D]+")).alias("word")).where("word <> ''")
    h = F.conv(F.substring(F.md5(F.col("word").cast("binary")), 1, 8), 16, 10).cast("long")
    signed = words.select("vec_id", (h % dim).cast("int").alias("bucket"), F.when(F.floor(h / dim) % 2 == 0, 1.0).otherwise(-1.0).alias("sign"))
    sums = signed.groupBy("vec_id", "bucket").agg(F.sum("sign").alias("v")).where("v <> 0")
    packed = sums.groupBy("vec_id").agg(F.map_from_entries(F.collect_list(F.struct("bucket", "v"))).alias("m"), F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))
    return packed.select("vec_id", F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda b: F.coalesce(F.try_element_at("m", b), F.lit(0.0)) / F.col("norm")).alias("embedding"))


def v_doc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "documents"), F.col("doc_id"), F.col("text"))


def v_bench(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "benchmark"), F.col("item_id"), F.col("text"))


def v_page(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "pages"), F.col("page_id"), F.regexp_replace("html", "<[^>]*>", " "))


def v_conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed_text(table(spark, sf_dir, "conversations"), F.col("conv_id") * 100 + F.col("turn"), F.col("text"))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "v_emb": v_emb, "v_line": v_line, "v_event": v_event, "v_doc": v_doc, "v_bench": v_bench, "v_page": v_page,
    "v_conv": v_conv, "v_part": v_part, "v_order": v_order, "v_cust": v_cust, "v_supp": v_supp,
}


def sanitize(points: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(good rows, rejected rows): an id and finite components of the commonest length are required."""
    lengths = points.where("embedding IS NOT NULL").groupBy(F.size("embedding").alias("n")).agg(F.count("*").alias("rows"))
    first = lengths.orderBy(F.desc("rows"), "n").first()
    dim = first["n"] if first else 0
    fine = F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") == dim) & F.lit(dim > 0)
    fine = F.coalesce(fine & F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))), F.lit(False))
    return points.where(fine), points.where(~fine)


def collapse_duplicates(points: DataFrame) -> DataFrame:
    """One row for each different vector: the smallest id, and how many rows it stands for.

    A zero distance breaks the analysis: a copy is never pruned, and copies fill a vertex's degree.
    """
    return points.groupBy("embedding").agg(F.min("vec_id").alias("vec_id"), F.count("*").alias("copies")).select("vec_id", "embedding", "copies")


def members_of_classes(points: DataFrame, classes: DataFrame) -> DataFrame:
    """(vec_id, class_id) of every row of ``points``; ``classes`` is what collapse_duplicates made of them."""
    named = classes.select("embedding", F.col("vec_id").alias("class_id"), "copies")
    return join_hot_apart(points.select("vec_id", "embedding"), named, "embedding", "copies").select("vec_id", "class_id")


def hold_out(points: DataFrame, every: int = 20) -> tuple[DataFrame, DataFrame]:
    """(base, queries): ids divisible by ``every`` are queries."""
    out = F.pmod(F.col("vec_id"), F.lit(every)) == 0
    return points.where(~out), points.where(out)
