"""The experiments' inputs, made from the given tables: instances with sparse features and labels.

features: instance_id, idx, val. labels: instance_id, label (and a name table where labels are words). A word is
a run of letters and digits in lower case; words are hashed to dims slots by md5.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bucketnet.functions.md5 import h32_many
from bucketnet.functions.seeds import h32
from bucketnet.sources.tables import load

SPLIT = r"[^\p{L}\p{N}]+"


def words(df: DataFrame, id_col: str, text_col: str = "text") -> DataFrame:
    """instance_id, place, word."""
    lower = F.split(F.lower(F.col(text_col)), SPLIT)
    return df.select(F.col(id_col).alias("instance_id"), F.posexplode(F.filter(lower, lambda w: w != "")).alias("place", "word"))


def hashed(words_df: DataFrame, dims: int) -> DataFrame:
    """instance_id, idx (int), val of distinct slots."""
    return words_df.select("instance_id", (h32(F.col("word")) % dims).cast("int").alias("idx")).distinct().withColumn("val", F.lit(1.0))


def slots(df: DataFrame, id_col: str, dims: int, text_col: str = "text") -> DataFrame:
    """instance_id, feats: the distinct slots of the row's words, one at least; made in the row, no word becomes a row."""
    distinct = F.array_distinct(F.filter(F.split(F.lower(F.col(text_col)), SPLIT), lambda w: w != ""))
    feats = F.array_distinct(F.transform(distinct, lambda w: (h32(w) % dims).cast("int")))
    made = df.select(F.col(id_col).alias("instance_id"), F.explode(F.array(feats)).alias("feats"))  # nothing goes below explode: feats are made once
    return made.where(F.size("feats") > 0)


def document_features(spark: SparkSession, sf_dir: str, dims: int) -> DataFrame:
    return hashed(words(load(spark, sf_dir, "documents"), "doc_id"), dims)


def canonical_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, canonical: the smallest id with the same text."""
    d = load(spark, sf_dir, "documents").select("doc_id", F.md5("text").alias("h"))
    first = d.groupBy("h").agg(F.min("doc_id").alias("canonical"))
    return d.join(first, "h").select("doc_id", "canonical")


VIEWS = 4


def known_item(spark: SparkSession, sf_dir: str, dims: int, seed: int = 11, views: int = VIEWS) -> DataFrame:
    """instance_id, view, idx, val, label: random halves of a document's distinct words find the document again (label: its canonical id).

    View -1 is the test half; views 0 .. views - 1 are other random halves, to train on.
    """
    d = words(load(spark, sf_dir, "documents"), "doc_id").select("instance_id", "word").distinct()
    d = d.withColumn("view", F.explode(F.sequence(F.lit(-1), F.lit(views - 1))))
    half = d.where(h32(seed, F.col("view"), F.col("instance_id"), F.col("word")) % 2 == 0)
    slots = half.select("instance_id", "view", (h32(F.col("word")) % dims).cast("int").alias("idx")).distinct()
    c = canonical_documents(spark, sf_dir).withColumnRenamed("canonical", "label")
    return slots.join(c, F.col("instance_id") == F.col("doc_id")).select("instance_id", "view", "idx", F.lit(1.0).alias("val"), "label")


def known_item_instances(spark: SparkSession, sf_dir: str, dims: int, seed: int = 11, views: int = VIEWS) -> DataFrame:
    """known_item as instances (instance_id, view, feats, vals of length 1, labels), made in the document's row: no word becomes a row."""
    d = load(spark, sf_dir, "documents").where("doc_id is not null and text is not null")
    d = d.select(F.col("doc_id").cast("long").alias("instance_id"), F.array_distinct(F.array_remove(F.split(F.lower("text"), SPLIT), "")).alias("words"))
    d = d.mapInArrow(_halves(dims, seed, views), "instance_id long, view int, feats array<int>")
    c = canonical_documents(spark, sf_dir).select("doc_id", F.array(F.col("canonical").cast("int")).alias("labels"))
    return with_values(d.join(c, F.col("instance_id") == F.col("doc_id")).select("instance_id", "view", "feats", "labels"))


def with_values(instances: DataFrame) -> DataFrame:
    """Instances of distinct slots with vals, all alike and of length 1 together: they can be made whenever the instances are read."""
    one = F.array_repeat((F.lit(1.0) / F.sqrt(F.size("feats").cast("double"))).cast("float"), F.size("feats"))
    return instances.select(*[c for c in instances.columns if c != "labels"], one.alias("vals"), "labels")


def _halves(dims: int, seed: int, views: int):
    """The task of known_item_instances: (instance_id, words) to a row a view that has a word."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 256):
                part = batch.slice(i, 256)
                ids, col = part.column("instance_id").to_numpy(), part.column("words")
                owner = np.repeat(np.arange(len(ids)), np.diff(col.offsets.to_numpy()))
                if len(owner) == 0:
                    continue
                words = col.flatten().cast(pa.large_binary())
                ends = np.frombuffer(words.buffers()[1], np.int64)[words.offset : words.offset + len(words) + 1]
                data, at, size = np.frombuffer(words.buffers()[2] or b"", np.uint8), ends[:-1], np.diff(ends)
                slot = (h32_many(data, at, size) % np.uint32(dims)).astype(np.int64)
                for view in range(-1, views):
                    prefix = [f"{seed}|{view}|{x}|".encode() for x in ids.tolist()]
                    width = np.array([len(x) for x in prefix])[owner]
                    kept = np.zeros(len(owner), bool)
                    for n in np.unique(width):
                        mine = np.flatnonzero(width == n)
                        rows = np.frombuffer(b"".join(x.ljust(n)[:n] for x in prefix), np.uint8).reshape(-1, n)[owner[mine]]
                        kept[mine] = h32_many(data, at[mine], size[mine], rows) % 2 == 0
                    key = np.unique(owner[kept] * dims + slot[kept])
                    count = np.bincount(key // dims, minlength=len(ids))
                    has = count > 0
                    feats = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(count[has])]).astype(np.int32)), pa.array((key % dims).astype(np.int32)))
                    yield pa.RecordBatch.from_arrays([pa.array(ids[has]), pa.array(np.full(int(has.sum()), view, np.int32)), feats], ["instance_id", "view", "feats"])

    return run


def strict_known_item(spark: SparkSession, sf_dir: str, dims: int, seed: int = 11) -> DataFrame:
    """Three quarters of the places of a document train, one quarter tests."""
    d = words(load(spark, sf_dir, "documents"), "doc_id")
    split = F.when(h32(seed, F.col("instance_id"), F.col("place")) % 4 < 3, "train").otherwise("test")
    slots = d.select("instance_id", split.alias("split"), (h32(F.col("word")) % dims).cast("int").alias("idx")).distinct()
    c = canonical_documents(spark, sf_dir).withColumnRenamed("canonical", "label")
    return slots.join(c, F.col("instance_id") == F.col("doc_id")).select("instance_id", "split", "idx", F.lit(1.0).alias("val"), "label")


def word_tagging(spark: SparkSession, sf_dir: str, min_label_docs: int = 2) -> tuple[DataFrame, DataFrame]:
    """(features words, labels): distinct words of the first half of a document, and those of the second half that occur as a label in min_label_docs documents."""
    d = words(load(spark, sf_dir, "documents"), "doc_id")
    n = d.groupBy("instance_id").agg(F.count(F.lit(1)).alias("n")).withColumnRenamed("instance_id", "n_id")
    halves = d.join(n, F.col("instance_id") == F.col("n_id")).select("instance_id", "word", (F.col("place") * 2 < F.col("n")).alias("first"))
    features = halves.where("first").select("instance_id", "word").distinct()
    labels = halves.where("not first").select("instance_id", "word").distinct()
    common = labels.groupBy("word").agg(F.count(F.lit(1)).alias("docs")).where(F.col("docs") >= min_label_docs).select("word")
    return features, labels.join(common, "word").select("instance_id", "word")


def copurchase(spark: SparkSession, sf_dir: str, seed: int = 11) -> DataFrame:
    """instance_id (order), part, is_label: the distinct parts of each order of two or more, one of them held out by md5 order."""
    parts = load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("instance_id"), F.col("l_partkey").alias("part")).distinct()
    held = parts.groupBy("instance_id").agg(F.count(F.lit(1)).alias("n"), F.min_by("part", F.struct(h32(seed, F.col("instance_id"), F.col("part")), "part")).alias("held")).where("n >= 2")
    held = held.withColumnRenamed("instance_id", "h_id")
    return parts.join(held, F.col("instance_id") == F.col("h_id")).select("instance_id", "part", (F.col("part") == F.col("held")).alias("is_label"))


def star_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order, feature: one-hot features of an order's customer, nation and region, and of its parts and suppliers."""
    o = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", "c_nationkey")
    n = load(spark, sf_dir, "nation").select("n_nationkey", "n_name", "n_regionkey")
    r = load(spark, sf_dir, "region")
    buyer = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    own = buyer.select("o_orderkey", F.explode(F.array(F.concat(F.lit("segment="), "c_mktsegment"), F.concat(F.lit("nation="), "n_name"), F.concat(F.lit("region="), "r_name"))).alias("feature"))
    li = load(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    p = load(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    s = load(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    sold = li.join(p, F.col("l_partkey") == F.col("p_partkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    items = sold.select(F.col("l_orderkey").alias("o_orderkey"), F.explode(F.array(F.concat(F.lit("brand="), "p_brand"), F.concat(F.lit("type="), "p_type"), F.concat(F.lit("supplied="), F.col("s_nationkey").cast("string")))).alias("feature"))
    return own.unionByName(items).distinct()


def small_labels(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    """instance_id, label of documents (lang, quality, toxic) or conversations (role; instance_id is conv_id * 1000 + turn)."""
    if kind == "lang":
        return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("instance_id"), F.col("lang").alias("label"))
    if kind == "role":
        return load(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("instance_id"), F.col("role").alias("label"))
    return load(spark, sf_dir, "labels").select(F.col("doc_id").alias("instance_id"), F.col(kind).cast("string").alias("label"))


def page_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """instance_id, place, word of pages without their tags."""
    bare = load(spark, sf_dir, "pages").withColumn("text", F.regexp_replace("html", "<[^>]*>", " "))
    return words(bare, "page_id")


def event_instances(events: DataFrame, dims: int) -> DataFrame:
    """event_id, ts, feats (array<int>), label (0 .. 9): hashed type, props.k and hour; works on streams."""
    k = F.get_json_object("props", "$.k")
    slots = [(h32(*x) % dims).cast("int") for x in (("t", F.col("event_type")), ("k", k), ("h", F.hour("ts").cast("string")))]
    return events.select("event_id", "ts", F.array_distinct(F.array(*slots)).alias("feats"), (F.col("user_id") % 10).cast("int").alias("label"))


def shingles(df: DataFrame, id_col: str, size: int, text_col: str = "text") -> DataFrame:
    """id, element (text of size words) as a set: what MinHash takes."""
    w = F.filter(F.split(F.lower(F.col(text_col)), SPLIT), lambda x: x != "")
    listed = df.select(F.col(id_col).alias("id"), w.alias("w")).where(F.size("w") >= size)
    spans = F.transform(F.sequence(F.lit(0), F.size("w") - size), lambda i: F.array_join(F.slice("w", i + 1, size), " "))
    return listed.select("id", F.explode(F.array_distinct(spans)).alias("element"))


def dataset_stats(features: DataFrame, labels: DataFrame, dims: int) -> DataFrame:
    """instances, used features, mean non-zeros, density, labels: one row, as a dataset table has it."""
    f = features.groupBy("instance_id").agg(F.count(F.lit(1)).alias("n"))
    a = f.agg(F.count(F.lit(1)).alias("instances"), F.avg("n").alias("mean_nonzeros"))
    u = features.agg(F.count_distinct("idx").alias("features"))
    label_count = labels.agg(F.count_distinct("label").alias("labels"))
    return a.join(F.broadcast(u)).join(F.broadcast(label_count)).select("instances", "features", "mean_nonzeros", (F.col("mean_nonzeros") / dims).alias("density"), "labels")
