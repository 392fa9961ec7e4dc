"""Line dedup by content-defined chunks of lines; DataFrame functions only.

Line hashes (32 bits of md5) roll over two lines: a chunk ends after line i where
31 * hash(i - 1) + hash(i) leaves no rest modulo spacing, so boundaries depend on the lines beside
them and move with the text when lines are put in before. A line of at least long_line words is
a chunk of its own. A chunk counts if it has min_words words and either two lines or a long one; words of a
line are its spaces plus one.

The lines at both ends of a repeated passage lie in chunks that hold some of what stands around it, and a short passage may have no whole
chunk. So from each line on, the fewest lines of passage_words words are a chunk as well, and so are the fewest lines of as many words up to
each line: these depend on the passage alone, and those inside a passage cover it, its first and last line too. Every repeated run of
whole lines of passage_words words or more goes, however it is broken into lines.

Of chunks that are equal line by line, the one with the smallest (doc_id, text hash, line) stays and the lines of the others go, within a
document too. A line that goes has an equal one at an earlier place, and the first of these stays.

Lines travel as 64-bit hashes. A chunk's key is made of its first line's hash, its number of lines and the sum of the hashes of its neighbouring
lines, a difference of two running sums; only chunks whose key repeats are read as text, and compared byte by byte. All steps before that work on a row per line,
so time grows with the number of lines, and a document's chunks are at most 3 rows a line. Texts are shuffled only of documents that have such a chunk, or
lose a line (a bitmap of their hashes tells most others apart, and a join all of them).

Null texts stay null; empty texts and texts without a repeated chunk are unchanged; rows with equal doc_id
and text are one document and change alike; a document can end empty, and stays. An empty table gives no rows. A task holds a document's lines and, as text,
those of its chunks whose key repeats: with lines of one word up to passage_words times the document, else two or three times.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bucketnet.llm.common import columns_of, cut, free_shuffles, fresh

LONG_LINE, MIN_WORDS, SPACING, PASSAGE_WORDS = 50, 20, 2, 51
BITS = 1 << 26  # 8 MB


def lines_of(docs: DataFrame) -> DataFrame:
    """id, th (hash of the text), i, h (hash of the line), m (what rolls), w (words): a row per line of each distinct document."""
    rows = docs.where("text is not null").select(F.col("doc_id").alias("id"), F.xxhash64("text").alias("th"), F.posexplode(F.split("text", "\n", -1)).alias("i", "x"))
    words = F.octet_length("x") - F.octet_length(F.replace("x", F.lit(" "), F.lit(""))) + 1
    rows = rows.select("id", "th", "i", F.xxhash64("x").alias("h"), F.conv(F.substring(F.md5("x"), 1, 8), 16, 10).cast("long").alias("m"), words.cast("long").alias("w"))
    return rows.groupBy("id", "th", "i").agg(*[F.min(c).alias(c) for c in ("h", "m", "w")])


def chunks_of(lines: DataFrame, long_line: int, min_words: int, spacing: int, passage_words: int) -> DataFrame:
    """id, th, a, b (first and last line) and key of each chunk that counts, each once."""
    doc = Window.partitionBy("id", "th")
    order = doc.orderBy("i")
    before, upto = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(Window.unboundedPreceding, 0)
    both = F.xxhash64(F.lag("h").over(order), "h").bitwiseAND(F.lit((1 << 38) - 1))  # 2**25 of them add up without overflow
    after = F.lead("w").over(order)
    ends = after.isNull() | (F.col("w") >= long_line) | (after >= long_line) | (F.pmod(F.coalesce(F.lag("m").over(order), F.lit(0)) * 31 + F.col("m"), F.lit(spacing)) == 0)
    placed = lines.withColumns({"from": F.coalesce(F.sum("w").over(before), F.lit(0)), "pair": both, "ends": ends})
    placed = placed.withColumns({"to": F.col("from") + F.col("w"), "sum": F.sum("pair").over(upto), "opens": F.coalesce(F.lag("ends").over(order), F.lit(True))})
    last = lambda c: F.last(F.when(F.col("opens"), F.col(c)), ignorenulls=True).over(upto)  # noqa: E731  of the line that opens the chunk
    ahead, back = doc.orderBy("from").rangeBetween(0, passage_words - 1), doc.orderBy("to").rangeBetween(1 - passage_words, 0)
    placed = placed.withColumns({
        "f_b": F.max("i").over(ahead), "f_to": F.max("to").over(ahead), "f_sum": F.max("sum").over(ahead),
        "g_a": F.min("i").over(back), "g_from": F.min("from").over(back), "g_sum": F.min("sum").over(back), "g_h": F.first("h").over(back),
        "c_a": last("i"), "c_from": last("from"), "c_sum": last("sum"), "c_h": last("h"),
    })

    def chunk(a: str, b: str, h: str, begin: str, end: str, counts: Column) -> Column:
        return F.struct(F.col(a).alias("a"), F.col(b).alias("b"), F.xxhash64(h, F.col(end) - F.col(begin), F.col(b) - F.col(a)).alias("key"), counts.alias("counts"))

    ahead_counts = F.col("f_to") - F.col("from") >= passage_words
    # with fewer words before the line itself, the run up to it is the one from its first line on
    back_counts = F.col("from") - F.col("g_from") >= passage_words
    size = F.col("to") - F.col("c_from")
    cut_counts = F.col("ends") & (size >= min_words) & ((F.col("i") > F.col("c_a")) | (F.col("w") >= long_line))
    cut_counts = cut_counts & ~((size >= passage_words) & (F.col("from") - F.col("c_from") < passage_words)) & ~(back_counts & (F.col("g_a") == F.col("c_a")))  # else one of the others
    found = F.array(chunk("i", "f_b", "h", "sum", "f_sum", ahead_counts), chunk("g_a", "i", "g_h", "g_sum", "sum", back_counts), chunk("c_a", "i", "c_h", "c_sum", "sum", cut_counts))
    return placed.select("id", "th", F.explode(F.filter(found, lambda c: c["counts"])).alias("c")).select("id", "th", "c.a", "c.b", "c.key")


def told_apart(rows: DataFrame, first: str, second: str, keys: DataFrame, k_first: str, k_second: str) -> tuple[DataFrame, DataFrame]:
    """rows in two: those whose (first, second) may be one of keys, which a join must still settle, and those whose is none of them.

    A broadcast bitmap of the hashes of keys, 16 bits a key up to BITS bits, and more rows in the first part beyond that.
    """
    bits = 1 << max(10, min(BITS.bit_length() - 1, (16 * keys.count()).bit_length()))
    slot = lambda a, b: F.pmod(F.xxhash64(a, b), F.lit(bits))
    w, bit, all_words = "__w", "__bit", "__words"
    words = keys.select(slot(k_first, k_second).alias(bit)).select(F.shiftright(bit, 6).alias(w), F.expr(f"shiftleft(1L, cast({bit} & 63 as int))").alias(bit)).groupBy(w).agg(F.bit_or(bit).alias(bit))
    each = rows.sparkSession.range(bits // 64).join(words, F.col("id") == F.col(w), "left").select(F.struct("id", F.coalesce(bit, F.lit(0).cast("long")).alias(bit)).alias(w))
    bitmap = cut(each.agg(F.sort_array(F.collect_list(w)).alias(w)).select(F.transform(w, lambda x: x[bit]).alias(all_words)))
    at = slot(first, second)
    held = F.get(all_words, F.shiftright(at, 6).cast("int")).bitwiseAND(F.call_function("shiftleft", F.lit(1).cast("long"), at.bitwiseAND(F.lit(63)).cast("int"))) != 0
    marked = rows.crossJoin(F.broadcast(bitmap))
    return marked.where(held).select(*columns_of(rows)), marked.where(~held).select(*columns_of(rows))


def chunk_texts(docs: DataFrame, parts: DataFrame, keys: DataFrame) -> DataFrame:
    """key, t (text), id, th, a, b of the chunks in parts whose key is in keys (again); rows of docs that repeat give theirs again."""
    spans = cut(parts.join(keys, F.col("key") == F.col("again"), "left_semi").groupBy("id", "th").agg(F.collect_set(F.struct("a", "b", "key")).alias("spans")))
    texts = docs.select(F.col("doc_id").alias("d_id"), F.xxhash64("text").alias("d_th"), "text")
    texts = told_apart(texts, "d_id", "d_th", spans, "id", "th")[0].join(spans, F.col("d_id").eqNullSafe(F.col("id")) & (F.col("d_th") == F.col("th"))).withColumn("lines", F.split("text", "\n", -1))
    as_text = F.transform("spans", lambda c: c.withField("t", F.array_join(F.slice("lines", c["a"] + 1, c["b"] - c["a"] + 1), "\n")))
    return texts.select("id", "th", F.explode(as_text).alias("c")).select("c.key", "c.t", "id", "th", "c.a", "c.b")


def compared(docs: DataFrame, parts: DataFrame) -> DataFrame:
    """key, texts (how many different ones), first and last place of each key that repeats."""
    again = cut(parts.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select(F.col("key").alias("again")))
    place = F.struct("id", "th", "a")
    by_text = chunk_texts(docs, parts, again).groupBy("key", "t").agg(F.min(place).alias("first"), F.max(place).alias("last"))
    return cut(by_text.groupBy("key").agg(F.count(F.lit(1)).alias("texts"), F.min("first").alias("first"), F.max("last").alias("last")))


def repeated_lines(docs: DataFrame, long_line: int = LONG_LINE, min_words: int = MIN_WORDS, spacing: int = SPACING, passage_words: int = PASSAGE_WORDS) -> DataFrame:
    """id, th (hash of the text) and gone (numbers of the lines to remove) of each document with any."""
    # written, so that the joins read exchanges on both sides, whose hot keys Spark can split
    parts = cut(chunks_of(lines_of(docs), long_line, min_words, spacing, passage_words))
    free_shuffles(docs.sparkSession)
    keys = compared(docs, parts)
    free_shuffles(docs.sparkSession)
    place, spans = F.struct("id", "th", "a"), ["id", "th", "a", "b"]
    one = keys.where((F.col("texts") == 1) & ~F.col("first").eqNullSafe(F.col("last"))).select(F.col("key").alias("f_key"), "first")
    later = parts.join(one, F.col("key") == F.col("f_key")).where(~place.eqNullSafe(F.col("first"))).select(spans)
    mixed = keys.where("texts > 1").select(F.col("key").alias("again"))
    if not mixed.isEmpty():  # other texts of the same key: by key and text
        found = cut(chunk_texts(docs, parts, mixed))
        first = found.groupBy("key", "t").agg(F.min(place).alias("first")).select(F.col("key").alias("f_key"), F.col("t").alias("f_t"), "first")
        found = found.join(cut(first), (F.col("key") == F.col("f_key")) & (F.col("t") == F.col("f_t"))).where(~place.eqNullSafe(F.col("first")))
        later = later.unionByName(found.select(spans))
    return cut(later.select("id", "th", F.explode(F.sequence("a", "b")).alias("i")).groupBy("id", "th").agg(F.collect_set("i").alias("gone")))


def dedup_lines(docs: DataFrame, long_line: int = LONG_LINE, min_words: int = MIN_WORDS, spacing: int = SPACING, passage_words: int = PASSAGE_WORDS) -> DataFrame:
    """docs, all columns and rows, with text less its repeated chunks, and two long columns last: its lines, and how many of them were removed.

    They are called _lines and _lines_removed, with more underscores before where docs has such columns.
    """
    g_id, g_th, gone, th, lines = fresh(docs, "__id", "__th", "__gone", "__text_hash", "__split")
    count, removed = fresh(docs, "_lines", "_lines_removed")
    by = repeated_lines(docs.select("doc_id", "text"), long_line, min_words, spacing, passage_words)
    by = by.select(F.col("id").alias(g_id), F.col("th").alias(g_th), F.col("gone").alias(gone))
    rows, whole = told_apart(docs.withColumn(th, F.xxhash64("text")), "doc_id", th, by, g_id, g_th)
    rows = rows.join(by, F.col("doc_id").eqNullSafe(F.col(g_id)) & (F.col(th) == F.col(g_th)), "left").drop(g_id, g_th)
    rows = rows.union(whole.withColumn(gone, F.lit(None).cast("array<int>"))).withColumn(lines, F.split("text", "\n", -1))
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), gone)
    text: Column = F.array_join(F.transform(kept, lambda i: F.get(lines, i)), "\n")
    number = F.coalesce(F.size(lines), F.lit(0)).cast("long")
    none = F.col(gone).isNull()
    rows = rows.withColumns({count: number, removed: F.when(none, 0).otherwise(F.size(gone)).cast("long"), "text": F.when(none, F.col("text")).otherwise(text)})
    return rows.select(*columns_of(docs), count, removed)
