"""Fuzzy deduplication as a plug-in for exact tags: a cluster's key stands in for the tag.

Word shingles, minwise bands as candidate buckets, exact similarity, connected components. Equal texts are one item
from the start. Within a bucket pairs are never listed: a few centres at a time are compared with all members outside
their component, until every member outside the bucket's largest component has been a centre.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.storage import discard, written
from .components import components


def shingle_set(text: Column, k: int = 5) -> Column:
    """Distinct hashes of a text's k-word shingles; a text of fewer words is one shingle, one without words none."""
    words = F.filter(F.split(text, "[ \\t\\n\\x0B\\f\\r]+"), lambda w: w != "")

    def of(words: Column) -> Column:
        n = F.size(words)
        many = F.array_distinct(F.transform(F.sequence(F.lit(1), n - (k - 1)), lambda i: F.xxhash64(F.concat_ws(" ", F.slice(words, i, k)))))
        return F.when(n >= k, many).when(n > 0, F.array(F.xxhash64(F.concat_ws(" ", words)))).otherwise(F.array().cast("array<bigint>"))

    # the words are bound to a lambda's variable, so they are split once and not for every shingle
    return F.element_at(F.transform(F.array(words), of), 1)


def jaccard(a: Column, b: Column) -> Column:
    """Similarity of two sets."""
    both = F.size(F.array_intersect(a, b))
    return both / (F.size(a) + F.size(b) - both)


def buckets(sets: DataFrame, bands: int, rows: int) -> DataFrame:
    """(id, bucket): one bucket per band, the hash of its minwise values."""
    low = lambda seed: F.array_min(F.transform("s", lambda x: F.xxhash64(x, F.lit(seed))))
    keys = F.array(*[F.xxhash64(F.lit(b), *[low(b * rows + r) for r in range(rows)]) for b in range(bands)])
    return sets.where(F.size("s") > 0).select("id", F.explode(keys).alias("bucket"))


def links(sets: DataFrame, placed: DataFrame, similarity: float, each: int = 16) -> DataFrame:
    """(u, v): verified links that connect every component which the buckets can show."""
    shared = placed.groupBy("bucket").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("bucket")
    members = written(placed.join(shared, "bucket"), "members")
    comps, done, out = members.select("id").distinct().select("id", F.col("id").alias("comp")), None, None
    while True:
        m = members.join(comps, "id")
        sizes = m.groupBy("bucket", "comp").agg(F.count(F.lit(1)).alias("n"))
        top = sizes.groupBy("bucket").agg(F.max_by("comp", F.struct("n", "comp")).alias("top"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
        todo = m.join(top, "bucket")
        todo = todo if out is None else todo.where("comp <> top")
        todo = todo if done is None else todo.join(done, ["bucket", "id"], "left_anti")
        w = Window.partitionBy("bucket").orderBy(F.xxhash64("id"), "id")
        centres = written(todo.withColumn("r", F.row_number().over(w)).where(F.col("r") <= each).select("bucket", "id", "comp"), "centres")
        if not centres.limit(1).count():
            return out if out is not None else members.sparkSession.createDataFrame([], "u long, v long")
        c = centres.select("bucket", F.col("id").alias("v"), F.col("comp").alias("c"))
        pairs = m.join(c, "bucket").where("comp <> c").select(F.least("id", "v").alias("u"), F.greatest("id", "v").alias("v")).distinct()
        a, b = sets.select(F.col("id").alias("u"), F.col("s").alias("su")), sets.select(F.col("id").alias("v"), F.col("s").alias("sv"))
        near = pairs.join(a, "u").join(b, "v").where((F.least(F.size("su"), F.size("sv")) >= similarity * F.greatest(F.size("su"), F.size("sv"))) & (jaccard(F.col("su"), F.col("sv")) >= similarity))
        new = written(near.select("u", "v"), "links")
        out = new if out is None else out.union(new)
        seen = centres.select("bucket", "id")
        done = seen if done is None else done.union(seen)
        found = components(out)
        comps = written(members.select("id").distinct().join(found.withColumnRenamed("node", "id"), "id", "left").select("id", F.coalesce("comp", "id").alias("comp")), "comps")
        discard(found)


def minhash_clusters(items: DataFrame, k: int = 5, bands: int = 20, rows: int = 4, similarity: float = 0.8) -> DataFrame:
    """(id, cluster) of items (id, content): the smallest id that links reach. Null contents are left out.

    With 20 bands of 4 values a pair of similarity 0.8 shares none with probability 3e-5.
    """
    texts = items.where("content IS NOT NULL").select("id", "content", F.sha2("content", 256).alias("same"))
    first = texts.groupBy("same").agg(F.min("id").alias("rep"))
    reps = texts.join(first, (texts["same"] == first["same"]) & (texts["id"] == first["rep"])).select(texts["id"], "content").dropDuplicates(["id"])
    sets = written(reps.select("id", shingle_set(F.col("content"), k).alias("s")), "shingle-sets")
    found = components(links(sets, written(buckets(sets, bands, rows), "bands"), similarity))
    named = first.join(found.withColumnRenamed("node", "rep"), "rep", "left").select("same", F.coalesce("comp", "rep").alias("cluster"))
    return texts.select("id", "same").join(named, "same").select("id", "cluster")


def minhash_tags(items: DataFrame, **options) -> DataFrame:
    """(sid, tag, item_id): records (sid, item_id, content) whose tag is the hash of their cluster, ready for the index."""
    clusters = minhash_clusters(items.select(F.col("item_id").alias("id"), "content"), **options)
    tagged = items.join(clusters.withColumnRenamed("id", "item_id"), "item_id")
    return tagged.groupBy("sid", F.unhex(F.sha2(F.col("cluster").cast("string"), 256)).alias("tag")).agg(F.min("item_id").alias("item_id"))
