"""Benchmark decontamination with DataFrame functions only.

Words are maximal runs outside the ASCII marks, after A-Z are lower-cased.  Every ten consecutive words of a benchmark
item form a window; an item of fewer words is one window.  The windows' hashes are the broadcast set.  Documents are
scanned once per window length: each position yields the hash of the words from there on, the hash join keeps the
candidates and the words themselves are compared.

The set is broadcast only up to BROADCAST_WINDOWS windows of BROADCAST_BYTES bytes; beyond it the same join runs as a shuffled one.

Null and empty texts, and texts without words, have no words and no hits.  Rows that repeat a doc_id are judged each
by its own text.  A null doc_id is a value like any other.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import fresh

WINDOW = 10
#: Bounds of the broadcast set: windows, and bytes of their words.
BROADCAST_WINDOWS, BROADCAST_BYTES = 1_000_000, 100_000_000
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Between words, before and after A-Z are lower-cased.
GAP_ANY = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
WORD_ANY = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"


def words_of(text: Column) -> Column:
    """The normalised words of a text, as an array."""
    plain = F.coalesce(text, F.lit(""))
    # lower() equals the A-Z mapping where all characters are ASCII; it is much the faster of the two.
    low = F.when(plain.rlike(r"[^\x00-\x7F]"), F.translate(plain, UPPER, LOWER)).otherwise(F.lower(plain))
    return F.array_remove(F.split(low, GAP_ANY), "")


def bench_windows(bench: DataFrame, window: int = WINDOW) -> DataFrame:
    """item_id, len, gram (array of words), h: the windows of each item; empty items have none."""
    items = bench.select("item_id", words_of(F.col("text")).alias("w")).filter(F.size("w") > 0)
    at = F.explode(F.sequence(F.lit(1), F.greatest(F.size("w") - (window - 1), F.lit(1)))).alias("at")
    return items.select("item_id", "w", at).select("item_id", F.slice("w", F.col("at"), F.lit(window)).alias("gram")).select("item_id", F.size("gram").alias("len"), "gram", F.xxhash64("gram").alias("h")).distinct()


def hits(docs: DataFrame, bench: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, row_key, pos (from 0), len, item_id: verified occurrences of windows in documents."""
    grams = bench_windows(bench, window)
    sizes = {r["len"]: r for r in grams.groupBy("len").agg(F.count("*").alias("n"), F.sum(F.octet_length(F.concat_ws(" ", "gram"))).alias("b")).collect()}  # at most `window` rows
    small = sum(r["n"] for r in sizes.values()) <= BROADCAST_WINDOWS and sum(r["b"] for r in sizes.values()) <= BROADCAST_BYTES
    words = docs.select("doc_id", F.xxhash64("text").alias("row_key"), words_of(F.col("text")).alias("w"))
    out = None
    for size in sorted(sizes) or [window]:
        right = grams.filter(F.col("len") == size)
        right = F.broadcast(right) if small else right
        at = words.filter(F.size("w") >= size).select("doc_id", "row_key", "w", F.explode(F.sequence(F.lit(0), F.size("w") - size)).alias("pos"))
        gram = F.slice("w", F.col("pos") + 1, F.lit(size))
        if not small:  # a shuffled join must not carry whole documents
            at = at.select("doc_id", "row_key", "pos", gram.alias("words"), F.xxhash64(gram).alias("key"))
            found = at.join(right, (F.col("key") == F.col("h")) & (F.col("words") == F.col("gram")))
        else:
            found = at.join(right, (F.xxhash64(gram) == F.col("h")) & (gram == F.col("gram")))
        found = found.select("doc_id", "row_key", "pos", "len", "item_id")
        out = found if out is None else out.unionByName(found)
    return out


def contamination(docs: DataFrame, bench: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, row_key, n_words, n_hit, spans (array of pos, end), items (array): one row per document row."""
    found = hits(docs, bench, window).groupBy("doc_id", "row_key").agg(F.sort_array(F.collect_set(F.struct("pos", "len"))).alias("at"), F.collect_set("item_id").alias("items"))
    # Windows merge into maximal spans: sorted by start, each either prolongs the last span or opens one.
    start = F.array().cast("array<struct<pos:int,end:int>>")

    def merge(acc: Column, x: Column) -> Column:
        end, last = x["pos"] + x["len"], F.element_at(acc, -1)
        longer = F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(F.struct(last["pos"].alias("pos"), F.greatest(last["end"], end).alias("end"))))
        return F.when((F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1))["end"] >= x["pos"]), longer).otherwise(F.concat(acc, F.array(F.struct(x["pos"].alias("pos"), end.alias("end")))))

    found = found.select("doc_id", "row_key", "items", F.aggregate("at", start, merge).alias("spans"))
    rows = docs.select("doc_id", F.xxhash64("text").alias("row_key"), F.size(words_of(F.col("text"))).cast("long").alias("n_words"))
    left, right = rows.alias("l"), found.alias("r")
    on = F.col("l.doc_id").eqNullSafe(F.col("r.doc_id")) & (F.col("l.row_key") == F.col("r.row_key"))
    spans = F.coalesce(F.col("r.spans"), start)
    return left.join(right, on, "left").select(
        "l.doc_id", "l.row_key", "n_words",
        F.aggregate(spans, F.lit(0).cast("long"), lambda a, s: a + (s["end"] - s["pos"])).alias("n_hit"),
        spans.alias("spans"),
        F.coalesce(F.col("r.items"), F.array().cast("array<bigint>")).alias("items"),
    )


def summary(docs: DataFrame, bench: DataFrame, window: int = WINDOW) -> DataFrame:
    """The digest of the registered query."""
    names = F.array_join(F.array_sort(F.transform("items", lambda i: i.cast("string"))), ",")
    return contamination(docs, bench, window).select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(names, 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


def remove(docs: DataFrame, bench: DataFrame, window: int = WINDOW, mode: str = "documents") -> DataFrame:
    """``docs`` without contaminated documents (mode "documents") or without the hit words (mode "spans").

    In mode "spans" a hit word goes together with the gap that follows it; all columns stay, in order.
    """
    ident, key, cuts = fresh(docs, "_hit_id", "_hit_key", "_spans")
    found = hits(docs, bench, window) if mode == "documents" else contamination(docs, bench, window).filter("n_hit > 0")
    ids = found.select(F.col("doc_id").alias(ident), F.col("row_key").alias(key), *([] if mode == "documents" else [F.col("spans").alias(cuts)])).distinct()
    on = docs["doc_id"].eqNullSafe(F.col(ident)) & (F.xxhash64(docs["text"]) == F.col(key))
    if mode == "documents":
        return docs.join(ids, on, "left_anti")
    joined = docs.join(ids, on, "left")
    gaps, words = F.split("text", WORD_ANY, -1), F.array_remove(F.split("text", GAP_ANY), "")
    kept = F.transform(words, lambda w, i: F.when(F.exists(cuts, lambda s: (i >= s["pos"]) & (i < s["end"])), "").otherwise(F.concat(w, F.element_at(gaps, i + 2))))
    text = F.when(F.col(cuts).isNull(), F.col("text")).otherwise(F.concat(F.element_at(gaps, 1), F.array_join(kept, "")))
    return joined.withColumn("text", text).select(*[F.col(f"`{c}`") for c in docs.columns])


SQL = r"""
WITH d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
b AS (
  SELECT item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM benchmark),
g AS (
  SELECT DISTINCT item_id, list_slice(w, i, i + 9) AS gram FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS i FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT len(gram) AS n FROM g),
win AS (SELECT doc_id, n, unnest(range(1, len(w) - n + 2)) AS i, w FROM d, sizes WHERE len(w) >= n),
hit AS (SELECT doc_id, i, n, item_id FROM win JOIN g ON list_slice(w, i, i + n - 1) = gram),
words AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY doc_id),
items AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN words USING (doc_id) LEFT JOIN items USING (doc_id)
"""
