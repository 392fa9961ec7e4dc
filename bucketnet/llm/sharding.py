"""Sharding by longest processing time: groups of equal texts, largest first, each to the shard with least.

The heap runs on the driver over classes of groups, not over groups, so what reaches the driver
has a fixed bound at any input size: groups of at least a 65,536th of all bytes (at most 65,536
of them) come one by one, the smaller ones as (size class, how many), exact to the byte below
65,536 and to a 1,024th above: at most some 180,000 classes, about 60 MB on the driver with 16 intervals each. A class of equal sizes is dealt by the heap's own rule, shard after
shard, without a step per group. The groups of a class then take their shard by their rank in it.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bucketnet.llm.common import cut, dense_rank_by, text_or_empty

EXACT_BELOW = 1 << 16
HEAVY_PART = 1 << 16


def deal(classes: list[tuple[float, int]], shards: int) -> list[list[tuple[int, int]]]:
    """For each class (size of a group, groups), largest first: how many of its groups each shard takes.

    The same as giving the groups one by one to the least-loaded shard (of equal loads the lowest
    number), but a class of c groups takes about shards * log(shards) steps.
    """
    heap = [(0.0, s) for s in range(shards)]
    out = []
    for size, count in classes:
        took = dict.fromkeys(range(shards), 0)
        while count:
            load, s = heap[0]
            if max(heap)[0] - load < size and count >= shards:  # every shard takes one before any takes two
                each = count // shards
                for _, x in heap:
                    took[x] += each
                heap = [(have + each * size, x) for have, x in heap]
                heapq.heapify(heap)
                count -= each * shards
                continue
            above = min(heap[1:3])[0] if shards > 1 else float("inf")
            n = int(max(1, min(count, (above - load) // size)))
            took[s] += n
            heapq.heapreplace(heap, (load + n * size, s))
            count -= n
        out.append([(s, n) for s, n in took.items() if n])
    return out


def shard_documents(docs: DataFrame, shards: int = 16) -> DataFrame:
    """Adds nothing to docs but returns doc_id, bytes, text_crc32, shard, slot for each of its rows.

    bytes: UTF-8 bytes of the text plus 1. Groups: rows of equal text; a null text counts as an empty
    one, of which the rows stay together. slot: 0, 1, 2, ... in each shard. A group heavier than
    a fair shard makes shards uneven; it is not split. Repeated rows are each kept; a null doc_id is
    an id like any other; an empty table gives no rows; other columns are not read. Of equally loaded shards the one with the lowest
    number takes a group; a text is only measured and hashed, whatever its length.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("t")).select(
        "doc_id", (F.octet_length("t") + 1).cast("long").alias("bytes"), F.crc32(F.col("t").cast("binary")).alias("text_crc32"), F.unhex(F.md5("t")).alias("g"))
    rows = cut(rows)
    groups = rows.groupBy("g").agg(F.sum("bytes").alias("size"), F.count(F.lit(1)).alias("n"))
    groups = cut(groups)
    total, many = groups.agg(F.sum("size"), F.count(F.lit(1))).first()
    heavy = max(1, -(-(total or 0) // HEAVY_PART))
    power = F.floor(F.log2(F.col("size") + F.lit(0.5)))
    rough = (F.col("size") / F.pow(F.lit(2.0), power) * 1024).cast("long") + power.cast("long") * 4096
    kind = F.when(F.col("size") < EXACT_BELOW, F.col("size")).otherwise(rough + EXACT_BELOW)
    kind = F.when((F.col("size") >= heavy) & (F.col("size") >= EXACT_BELOW), -F.col("size")).otherwise(kind)
    groups = groups.withColumn("kind", kind)
    sizes = groups.groupBy("kind").agg(F.sum("size").alias("s"), F.count(F.lit(1)).alias("c")).collect()  # at most 65,536 + 65,536 + 1,024 * 47 rows
    classes = sorted(((r.s / r.c, r.c, r.kind) for r in sizes), reverse=True)
    quotas, at = [], {}
    for (_, _, k), shares in zip(classes, deal([(s, c) for s, c, _ in classes], shards), strict=True):
        at[k] = 0
        for s, n in shares:
            quotas.append((k, at[k], at[k] + n, s))
            at[k] += n
    # a class has at most one interval a shard, so this table is bounded like the classes
    plan = spark.createDataFrame(quotas, "q_kind long, q_from long, q_to long, shard int")
    plan = plan.groupBy("q_kind").agg(F.array_sort(F.collect_list(F.struct("q_to", "shard"))).alias("q"))
    buckets = max(8, (many or 0) // 200_000)
    ranked = dense_rank_by(groups.select("g", "kind"), ["kind"], ["g"], "rank", buckets)
    placed = (ranked.join(plan, F.col("kind") == F.col("q_kind"))
              .select(F.col("g").alias("p_g"), F.filter("q", lambda x: x["q_to"] > F.col("rank"))[0]["shard"].alias("shard")))
    out = rows.join(placed, F.col("g") == F.col("p_g")).drop("p_g")
    out = dense_rank_by(out, ["shard"], ["doc_id", "text_crc32"], "slot", max(32, (many or 0) // 50_000))
    return out.select("doc_id", "bytes", "text_crc32", "shard", "slot")
