"""Relations over the given tables: base tables, assembled dialogs, sentences and hashed text vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

DIM = 64


def base(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def dialogs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per conversation with its turns in order."""
    turns = F.sort_array(F.collect_list(F.struct("turn", "role", "text")))
    df = base(spark, sf_dir, "conversations").groupBy("conv_id").agg(turns.alias("turns"))
    return df.select(
        "conv_id", (F.col("conv_id") % 6).alias("entity"), F.size("turns").cast("long").alias("n_turns"), "turns",
        F.array_join(F.transform("turns", lambda t: t["text"]), " ").alias("text_all"), F.col("turns")[0]["role"].alias("first_role"),
    )


#: SQL of the relations that are not tables, for DuckDB.
DIALOGS_SQL = """(SELECT conv_id, conv_id % 6 AS entity, count(*) AS n_turns, string_agg(text, ' ' ORDER BY turn, role, text) AS text_all,
 arg_min(role, turn) AS first_role FROM conversations GROUP BY conv_id)"""
CUSTOMERS_SQL = "(SELECT c.*, n_nationkey, n_name, r_regionkey, r_name FROM customer c JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    nation, region = base(spark, sf_dir, "nation"), base(spark, sf_dir, "region")
    places = nation.join(region, nation.n_regionkey == region.r_regionkey)
    return base(spark, sf_dir, "customer").join(places, F.col("c_nationkey") == F.col("n_nationkey"))


#: relation name -> (key columns, attribute that holds text)
RELATIONS = {
    "documents": (("doc_id",), "text"), "dialogs": (("conv_id",), "text_all"), "events": (("event_id",), "event_type"),
    "lineitem": (("l_orderkey", "l_linenumber"), "l_returnflag"), "customers": (("c_custkey",), "c_name"), "pages": (("page_id",), "html"),
}


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name == "dialogs":
        return dialogs(spark, sf_dir)
    if name == "customers":
        return customers(spark, sf_dir)
    return base(spark, sf_dir, name)


def relation_sql(name: str) -> str:
    return {"dialogs": DIALOGS_SQL, "customers": CUSTOMERS_SQL}.get(name, name)


def stems(text: Column) -> Column:
    """First five letters of each lower-case word."""
    return F.transform(F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), ""), lambda w: F.substring(w, 1, 5))


def embed_tuples(df: DataFrame, text: str, dim: int = DIM) -> DataFrame:
    """Adds `vec`, hashed term frequencies of unit length: the ingestion step's stand-in for an embedding model."""
    slots = F.transform(stems(F.coalesce(F.col(text), F.lit(""))), lambda w: F.pmod(F.xxhash64(w), F.lit(dim)).cast("int"))
    df = df.withColumn("_slots", slots)
    counts = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda i: F.size(F.filter("_slots", lambda s: s == i)).cast("double"))
    df = df.withColumn("_raw", counts)
    norm = F.sqrt(F.aggregate("_raw", F.lit(0.0), lambda a, x: a + x * x))
    df = df.withColumn("_norm", norm)
    return df.withColumn("vec", F.transform("_raw", lambda x: F.when(F.col("_norm") > 0, x / F.col("_norm")).otherwise(F.lit(0.0)).cast("float"))).drop("_slots", "_raw", "_norm")


def sentences(df: DataFrame, key: str, text: str) -> DataFrame:
    """key, sent_no, sent: pieces between line ends and sentence ends."""
    return df.select(key, F.posexplode(F.filter(F.split(text, r"\n|(?<=[.!?])\s+"), lambda s: F.length(F.trim(s)) > 0)).alias("sent_no", "sent"))
