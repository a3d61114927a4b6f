"""Benchmark decontamination with DataFrame operators alone.

Benchmark items give windows of ``n`` consecutive words (an item of fewer words
is one window).  Each window has an anchor, its longest word.  Documents are
exploded to words inside one code-generated stage and meet a broadcast hash
table of anchors; the few matches are tested on the window's first and last
word, then on its text.  No document text is shuffled: only hits are.  Where
the window table is larger than ``BROADCAST_WINDOWS`` rows the same join runs
without the broadcast, on slices of words around each position.
"""

from __future__ import annotations

from string import ascii_lowercase, ascii_uppercase

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed value: what separates words, after A-Z became a-z.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Window rows that are broadcast; about 200 bytes each.
BROADCAST_WINDOWS = 500_000


def words_of(text: Column) -> Column:
    """The words of a text; none for null or empty text."""
    low = F.translate(F.coalesce(text, F.lit("")), ascii_uppercase, ascii_lowercase)
    return F.array_remove(F.split(low, SEPARATORS), "")


def benchmark_windows(benchmark: DataFrame, n: int = 10, text: str = "text", item_id: str = "item_id") -> DataFrame:
    """``(anchor, shift, size, head, tail, window, items)``, one row per different window text.

    ``shift`` is the anchor's place in the window, ``items`` the ids (as
    strings) of the items that hold it.  Items without words give nothing;
    an item with a null id is named by the empty string.
    """
    items = benchmark.select(F.coalesce(F.col(item_id).cast("string"), F.lit("")).alias("item"), words_of(F.col(text).cast("string")).alias("w")).where(F.size("w") > 0)
    size = F.least(F.lit(n), F.size("w"))
    starts = items.select("item", "w", size.alias("size"), F.explode(F.sequence(F.lit(1), F.size("w") - size + 1)).alias("at"))
    cut = starts.select("item", "size", F.slice("w", F.col("at"), F.col("size")).alias("g"))
    texts = cut.groupBy(F.array_join("g", " ").alias("window"), "size").agg(F.array_sort(F.collect_set("item")).alias("items"), F.first("g").alias("g"))
    longest = F.array_sort("g", lambda a, b: F.when(F.length(a) != F.length(b), F.length(b) - F.length(a)).when(a < b, -1).when(a > b, 1).otherwise(0))[0]
    anchored = texts.withColumn("anchor", longest)
    return anchored.select("anchor", (F.array_position("g", F.col("anchor")).cast("int") - 1).alias("shift"), "size", F.col("g")[0].alias("head"), F.element_at("g", -1).alias("tail"), "window", "items")


def _row_key(doc_id: str, text: str) -> Column:
    """Names a row by what the result depends on; rows that repeat share it."""
    return F.struct(F.col(doc_id).alias("i"), F.xxhash64(text).alias("h"), F.xxhash64(F.lit(7), text).alias("g"))


def window_hits(docs: DataFrame, windows: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """``(key, start, size, items)`` for each occurrence of a window; ``start`` counts words from 0."""
    small = windows.count() <= BROADCAST_WINDOWS
    most = windows.agg(F.max("size")).first()[0] or 1
    rows = docs.select(_row_key(doc_id, text).alias("key"), words_of(F.col(text)).alias("w"))
    words = rows.select("key", "w", F.posexplode("w").alias("pos", "word"))
    if small:
        near, first = words, F.lit(0)
        windows = F.broadcast(windows)
    else:
        first = F.greatest(F.lit(0), F.col("pos") - most + 1)
        near = words.select("key", "pos", "word", F.slice("w", first + 1, F.lit(2 * most)).alias("w"))
    start = F.col("pos") - F.col("shift")
    at = start - first
    met = near.join(windows, F.col("word") == F.col("anchor")).where((at >= 0) & (F.size("w") - at >= F.col("size")))
    ends = (F.get("w", at) == F.col("head")) & (F.get("w", at + F.col("size") - 1) == F.col("tail"))
    same = F.array_join(F.slice("w", F.greatest(at + 1, F.lit(1)), F.col("size")), " ") == F.col("window")
    return met.where(ends).where(same).select("key", start.alias("start"), "size", "items")


def _merged(hits: Column) -> Column:
    """Sorted (start, end) structs -> disjoint spans in order."""
    none = F.array().cast("array<struct<start:int,end:int>>")

    def step(done: Column, x: Column) -> Column:
        last = F.element_at(done, -1)
        joined = F.concat(F.slice(done, 1, F.greatest(F.size(done) - 1, F.lit(0))), F.array(F.struct(last["start"].alias("start"), F.greatest(last["end"], x["end"]).alias("end"))))
        return F.when((F.size(done) > 0) & (x["start"] <= F.try_element_at(done, F.lit(-1))["end"]), joined).otherwise(F.concat(done, F.array(x)))

    return F.aggregate(F.array_sort(hits), none, step)


def contaminated_spans(docs: DataFrame, benchmark: DataFrame, n: int = 10, text: str = "text", doc_id: str = "doc_id", item_text: str = "text", item_id: str = "item_id") -> DataFrame:
    """``(key, spans, items)`` for rows with hits: disjoint word spans and sorted item ids."""
    hits = window_hits(docs, benchmark_windows(benchmark, n, item_text, item_id), text, doc_id)
    by = hits.groupBy("key").agg(F.collect_set(F.struct(F.col("start").cast("int").alias("start"), (F.col("start") + F.col("size")).cast("int").alias("end"))).alias("hits"), F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("items"))
    return by.select("key", _merged(F.col("hits")).alias("spans"), "items")


def contamination(docs: DataFrame, benchmark: DataFrame, n: int = 10, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """One row per document: ``doc_id, n_words, n_hit, n_items, items_sha256, contaminated``.

    Null or empty texts have no words and no hits.  Repeated rows stay, each with
    its result; an empty benchmark or document table is no error.
    """
    docs = docs.select(F.col(doc_id).alias("doc_id"), F.col(text).cast("string").alias("text"))
    spans = contaminated_spans(docs, benchmark, n, "text", "doc_id")
    base = docs.select("doc_id", _row_key("doc_id", "text").alias("key"), F.size(words_of(F.col("text"))).cast("bigint").alias("n_words"))
    hit = F.aggregate("spans", F.lit(0), lambda a, x: a + x["end"] - x["start"])
    joined = base.join(spans.select(F.col("key").alias("k"), hit.cast("bigint").alias("hit"), "items"), _same_key("key", "k"), "left")
    items = F.coalesce("items", F.array().cast("array<string>"))
    return joined.select("doc_id", "n_words", F.coalesce("hit", F.lit(0).cast("bigint")).alias("n_hit"), F.size(items).cast("bigint").alias("n_items"), F.sha2(F.array_join(items, ",").cast("binary"), 256).alias("items_sha256"), (F.coalesce("hit", F.lit(0)) > 0).alias("contaminated"))


def _same_key(a: str, b: str) -> Column:
    return F.col(f"{a}.i").eqNullSafe(F.col(f"{b}.i")) & (F.col(f"{a}.h") == F.col(f"{b}.h")) & (F.col(f"{a}.g") == F.col(f"{b}.g"))


def remove_spans(docs: DataFrame, benchmark: DataFrame, n: int = 10, text: str = "text", doc_id: str = "doc_id", drop_documents: bool = False) -> DataFrame:
    """``docs`` without benchmark windows: hit words go with what separates them
    from the next word, and a text left without words goes altogether.  With
    ``drop_documents`` every document that has a hit goes instead."""
    spans = contaminated_spans(docs, benchmark, n, text, doc_id).select(F.col("key").alias("__k"), F.col("spans").alias("__spans"))
    keyed = docs.withColumn("__key", _row_key(doc_id, text))
    if drop_documents:
        return keyed.join(spans, _same_key("__key", "__k"), "left_anti").drop("__key")
    joined = keyed.join(spans, _same_key("__key", "__k"), "left")
    word = r"(?i)[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
    gap = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"
    pieces = F.regexp_extract_all(F.col(text), F.lit(f"{word}{gap}*"), F.lit(0))
    left = F.filter(pieces, lambda x, i: ~F.exists("__spans", lambda s: (i >= s["start"]) & (i < s["end"])))
    cleaned = F.concat(F.regexp_extract(F.col(text), f"^{gap}*", 0), F.array_join(left, ""))
    out = joined.withColumn(text, F.when(F.col("__spans").isNull(), F.col(text)).otherwise(cleaned))
    return out.where(F.col("__spans").isNull() | (F.size(words_of(F.col(text))) > 0)).drop("__key", "__k", "__spans")
