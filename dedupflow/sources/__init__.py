"""Tables, files and streams that clients' records come from."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

FORMATS = ("parquet", "orc", "csv", "json", "text")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables; columns are pruned by what is selected."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options) -> DataFrame:
    """Files of a format with an explicit schema (nothing is inferred); text files have one column, ``value``."""
    if fmt not in FORMATS:
        raise ValueError(f"format {fmt} is none of {FORMATS}")
    reader = spark.read.format(fmt).options(**options)
    return (reader if fmt in ("parquet", "orc", "text") and schema is None else reader.schema(schema or "value string")).load(path)


def client_of(source: Column) -> Column:
    """Client number in a name such as ``src7``."""
    return F.substring(source, 4, 20).cast("long")


def items(df: DataFrame, sid: Column, item_id: Column, content: Column, unit: str = "doc") -> DataFrame:
    """(sid, item_id, content): the records of clients as whole texts, non-blank lines or paragraphs.

    Null contents give no record (see ``rejects``); the empty text is a record. Lines are trimmed of spaces; a line's
    item_id is its text's times 2^20 plus its position.
    """
    base = df.select(sid.alias("sid"), item_id.alias("item_id"), content.alias("content")).where("content IS NOT NULL")
    if unit == "doc":
        return base
    parts = {"line": "\n", "para": "\n[ \t]*\n"}[unit]
    split = base.select("sid", "item_id", F.posexplode(F.split("content", parts)).alias("pos", "part"))
    return split.select("sid", (F.shiftleft("item_id", 20) + F.col("pos")).alias("item_id"), F.trim("part").alias("content")).where("content <> ''")


def rejects(df: DataFrame, item_id: Column, content: Column) -> DataFrame:
    """Rows that cannot be tagged: null contents."""
    return df.select(item_id.alias("item_id"), content.alias("content")).where("content IS NULL").select("item_id")


def documents(spark: SparkSession, sf_dir: str, unit: str = "doc") -> DataFrame:
    """Records of the documents table, a client per source."""
    return items(table(spark, sf_dir, "documents"), client_of(F.col("source")), F.col("doc_id"), F.col("text"), unit)


def parts_by_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dense overlap: a client per supplier, parts as records."""
    return table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("sid"), F.col("l_partkey").alias("item_id"), F.col("l_partkey").cast("string").alias("content")).distinct()


def pages_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, host, text): pages without scripts, styles and tags."""
    bare = F.regexp_replace(F.regexp_replace("html", "(?is)<(script|style)[^>]*>.*?</\\1>", " "), "<[^>]+>", " ")
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("host"), F.trim(F.regexp_replace(bare, "\\s+", " ")).alias("text"))


def conversations(spark: SparkSession, sf_dir: str, clients: int = 10) -> DataFrame:
    """Turns of conversations dealt to ``clients``: a control without copies."""
    return table(spark, sf_dir, "conversations").select(F.pmod("conv_id", F.lit(clients)).alias("sid"), (F.col("conv_id") * 1000 + F.col("turn")).alias("item_id"), F.col("text").alias("content")).where("content IS NOT NULL")


def beats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(sid, ts, beat_id): events as heartbeats of their users."""
    return table(spark, sf_dir, "events").select(F.col("user_id").alias("sid"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("beat_id"))
