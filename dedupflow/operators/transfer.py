"""Model files in numbered chunks with a digest each: a transfer resumes where it broke off."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def split(files: DataFrame, size: int = 65536) -> DataFrame:
    """(file_id, seq, offset, data, digest) of files (file_id, data); an empty file is one empty chunk."""
    n = F.greatest(F.lit(1), F.ceil(F.octet_length("data") / size)).cast("int")
    cut = F.transform(F.sequence(F.lit(0), n - 1), lambda i: F.substring(F.col("data"), i * size + 1, F.lit(size)))
    parts = files.select("file_id", F.posexplode(cut).alias("seq", "data"))
    return parts.select("file_id", "seq", (F.col("seq") * size).cast("long").alias("offset"), "data").withColumn("digest", F.sha2("data", 256))


def verify(chunks: DataFrame) -> DataFrame:
    """Chunks with ``ok``: whether the data still has its digest."""
    return chunks.withColumn("ok", F.sha2("data", 256) == F.col("digest"))


def resume_from(manifest: DataFrame, received: DataFrame) -> DataFrame:
    """(file_id, seq): chunks still to send, those missing and those that arrived damaged."""
    good = verify(received).where("ok").select("file_id", "seq", "digest")
    return manifest.join(good, ["file_id", "seq", "digest"], "left_anti").select("file_id", "seq")


def assemble(chunks: DataFrame) -> DataFrame:
    """(file_id, data): files put together in order; one model file fits a task by definition."""
    packed = chunks.groupBy("file_id").agg(F.array_sort(F.collect_list(F.struct("seq", F.hex("data").alias("h")))).alias("p"))
    return packed.select("file_id", F.unhex(F.concat_ws("", "p.h")).alias("data"))
