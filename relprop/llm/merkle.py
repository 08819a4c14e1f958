"""Document fingerprints: a Merkle tree over sections, paragraphs and chunks, with DataFrame functions only.

A section ends with a blank line, a paragraph with a line, a chunk after a mark of punctuation or after a word with one
of a few last letters (so that chunks of three words or so come back to the same places behind an edit).  Every part
keeps its separators: the chunks of a text, put together, are the text.  A chunk's hash covers its characters; a
paragraph's covers its chunks' hashes, a section's its paragraphs', the root its sections'.

A fingerprint is ``root:nodes``: 32 hex digits, then the KEPT smallest distinct hashes of the tree's nodes below the
root (chunks, paragraphs and sections), 8 hex digits each, in order.  Likeness of two fingerprints is 1 where the roots
agree, else the share of common hashes among the KEPT smallest of both together: the Jaccard likeness of the two trees'
nodes, exact up to KEPT nodes and a bottom-k estimate beyond, so that a fingerprint has a bounded size.

Null texts are empty ones.  The empty text has one empty chunk.  Ties in doc_id are ordered by text hash; rows without
a doc_id come last.  Rows that repeat are rows like any other; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import fresh

KEPT = 128
BUCKET = 256
#: A section with the blank lines behind it, whatever blanks they hold; it matches the empty end of a text as well.
SECTION = r"(?s).*?(?:\n[ \t]*\n(?=[^\n])|\z)"
PARAGRAPH_END = r"(?<=\n)(?=[^\n])"
CHUNK_END = r"(?<=[.!?,;|*%&$#]\s)|(?<=[eoad]\s)"


def chunks(paragraph: Column) -> Column:
    return F.split(paragraph, CHUNK_END)


def node_hash(children: Column) -> Column:
    return F.md5(F.array_join(children, "").cast("binary"))


def leaf_hash(chunk: Column) -> Column:
    return F.substring(F.hex(F.xxhash64(chunk)), -8, 8)


def tree(text: Column) -> Column:
    """array<struct<hash, paragraphs: array<struct<hash, leaves: array<string>>>>>: the sections of a text."""
    plain = F.coalesce(text, F.lit(""))

    def paragraph(p: Column) -> Column:
        leaves = F.transform(chunks(p), lambda c: F.lpad(F.hex(F.xxhash64(c)), 16, "0"))
        return F.struct(node_hash(leaves).alias("hash"), leaves.alias("leaves"))

    def section(s: Column) -> Column:
        return F.transform(F.split(s, PARAGRAPH_END), paragraph)

    # The empty text is one empty section.
    parts = F.array_remove(F.regexp_extract_all(plain, F.lit(SECTION), F.lit(0)), "")
    sections = F.transform(F.when(plain == "", F.array(F.lit(""))).otherwise(parts), section)
    return F.transform(sections, lambda ps: F.struct(node_hash(F.transform(ps, lambda p: p["hash"])).alias("hash"), ps.alias("paragraphs")))


def fingerprint_of(tree_col: Column, kept: int = KEPT) -> Column:
    root = node_hash(F.transform(tree_col, lambda s: s["hash"]))
    inner = lambda h: F.upper(F.substring(h, 1, 8))
    below = lambda p: F.concat(F.transform(p["leaves"], lambda h: F.substring(h, 9, 8)), F.array(inner(p["hash"])))
    found = F.flatten(F.transform(tree_col, lambda s: F.concat(F.flatten(F.transform(s["paragraphs"], below)), F.array(inner(s["hash"])))))
    low = F.array_sort(F.array_distinct(found))
    return F.lower(F.concat(root, F.lit(":"), F.array_join(F.slice(low, 1, kept), "")))


def with_fingerprint(df: DataFrame, text: str = "text", out: str = "fingerprint") -> DataFrame:
    """Add the fingerprint of ``text``; the tree is computed once a row."""
    (held,) = fresh([*df.columns, out], "_tree")
    return df.withColumn(held, tree(F.col(text))).withColumn(out, fingerprint_of(F.col(held))).drop(held)


def likeness(a: Column, b: Column, kept: int = KEPT) -> Column:
    """0 to 1, from two fingerprints alone."""
    leaves = lambda f: F.split(F.substring(f, 34, 8 * kept), r"(?<=\G.{8})(?=.)")
    both = F.slice(F.array_sort(F.array_union(leaves(a), leaves(b))), 1, kept)
    common = F.size(F.array_intersect(both, F.array_intersect(leaves(a), leaves(b))))
    return F.when(F.substring(a, 1, 32) == F.substring(b, 1, 32), 1.0).otherwise(common / F.size(both))


def nodes(docs: DataFrame) -> DataFrame:
    """doc_id, section, paragraph, section_hash, paragraph_hash, n_leaves: the inner nodes of every tree."""
    s = docs.select("doc_id", F.posexplode(tree(F.col("text"))).alias("section", "s"))
    p = s.select("doc_id", "section", F.col("s.hash").alias("section_hash"), F.posexplode("s.paragraphs").alias("paragraph", "p"))
    return p.select("doc_id", "section", "paragraph", "section_hash", F.col("p.hash").alias("paragraph_hash"), F.size("p.leaves").alias("n_leaves"))


def edits(pairs: DataFrame, old: str = "old", new: str = "new") -> DataFrame:
    """Add changed: array<struct<side, section, paragraph>>, the branches in which two texts differ, top down.

    Sections are matched by their hashes wherever they stand and not descended into; of the others, paragraphs whose
    hash the other text's unmatched sections do not hold are reported, of side "old" where they are gone and "new" where
    they came.  Where nothing but order or repetition differs, the paragraphs that differ by position are reported.
    """
    names = fresh([*pairs.columns, "changed"], "_a", "_b", "_x", "_y", "_c")
    a, b, x, y, c = names
    hashes = lambda nodes: F.transform(nodes, lambda n: n["hash"])
    places = lambda t: F.flatten(F.transform(t, lambda s, i: F.transform(s["paragraphs"], lambda p, j: F.struct(i.alias("section"), j.alias("paragraph"), s["hash"].alias("above"), p["hash"].alias("hash")))))
    open_ = lambda own, other: F.filter(places(F.col(own)), lambda p: F.array_contains(F.array_except(hashes(F.col(own)), hashes(F.col(other))), p["above"]))
    df = pairs.withColumn(a, tree(F.col(old))).withColumn(b, tree(F.col(new)))
    df = df.withColumn(x, open_(a, b)).withColumn(y, open_(b, a))

    def side(name: str, own: str, other: str) -> Column:
        lost = F.array_except(hashes(F.col(own)), hashes(F.col(other)))
        return F.transform(F.filter(own, lambda p: F.array_contains(lost, p["hash"])), lambda p: F.struct(F.lit(name).alias("side"), p["section"].alias("section"), p["paragraph"].alias("paragraph")))

    def by_place(name: str, own: str, other: str) -> Column:
        mine, theirs = places(F.col(own)), places(F.col(other))
        marked = F.transform(mine, lambda p, i: F.struct(F.lit(name).alias("side"), p["section"].alias("section"), p["paragraph"].alias("paragraph"), (~F.coalesce(F.get(theirs, i)["hash"] == p["hash"], F.lit(False))).alias("off")))
        return F.transform(F.filter(marked, lambda m: m["off"]), lambda m: F.struct(m["side"].alias("side"), m["section"].alias("section"), m["paragraph"].alias("paragraph")))

    df = df.withColumn(c, F.concat(side("old", x, y), side("new", y, x)))
    same = F.to_json(hashes(F.col(a))) == F.to_json(hashes(F.col(b)))
    return df.withColumn("changed", F.when(same | (F.size(c) > 0), F.col(c)).otherwise(F.concat(by_place("old", a, b), by_place("new", b, a)))).drop(*names)


def next_smaller(keys: DataFrame, span: int, width: int = BUCKET) -> DataFrame:
    """k, next: for each of distinct longs k >= 0, all below ``span``, the largest one below it (null at the end).

    Buckets of ``width`` values are ordered within; between buckets the same is done with the bucket numbers, which
    are ``width`` times closer.  No task sees more than ``width`` keys of a bucket, whatever the keys are.
    """
    if span <= width:
        return keys.select("k", F.lead("k").over(W.orderBy(F.desc("k"))).alias("next"))
    b = keys.select("k", F.expr(f"k div {width}").alias("b"))
    inside = b.select("k", "b", F.lead("k").over(W.partitionBy("b").orderBy(F.desc("k"))).alias("inner"))
    tops = b.groupBy("b").agg(F.max("k").alias("top"))
    after = next_smaller(tops.select(F.col("b").alias("k")), span // width + 1, width)
    follow = after.select(F.col("k").alias("fb"), F.col("next").alias("nb")).join(tops.select(F.col("b").alias("tb"), "top"), F.col("nb") == F.col("tb")).select("fb", "top")
    return inside.join(follow, F.col("b") == F.col("fb"), "left").select("k", F.coalesce("inner", "top").alias("next"))


def with_next(docs: DataFrame, text: str = "text", out: str = "next_text", carry: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, ``text``, ``out``: each document with the text of the one that follows in descending doc_id, in a ring.

    ``carry``: further columns to take along; next_ of each is null where the follower comes from another bucket.

    Texts are shuffled once, into buckets of BUCKET consecutive ids; only the first text of each bucket travels again.
    """
    base = docs.select("doc_id", F.coalesce(text, F.lit("")).alias(text), *carry)
    low, high = base.agg(F.min("doc_id"), F.max("doc_id")).first()
    low, high = (low // BUCKET, high // BUCKET) if low is not None else (0, 0)
    # Rows without an id get bucket -1 - x, behind all others, spread by their text.  Quotients do not overflow.
    b = F.coalesce(F.shiftright("doc_id", BUCKET.bit_length() - 1) - F.lit(low), F.lit(-1) - F.pmod(F.xxhash64(text), F.lit(BUCKET)))
    rows = base.select("doc_id", text, *carry, b.alias("b"))
    order = [F.desc_nulls_last("doc_id"), F.xxhash64(text)]
    inside = rows.withColumn("inner", F.lead(F.struct(text, *carry)).over(W.partitionBy("b").orderBy(*order)))
    heads = rows.groupBy("b").agg(F.max_by(text, F.struct(F.coalesce("doc_id", F.lit(0)).alias("i"), F.bitwise_not(F.xxhash64(text)).alias("t"))).alias("head"))
    n = high - low + 1 + BUCKET
    keys = rows.select((F.col("b") + BUCKET).alias("k")).distinct()
    ring = next_smaller(keys, n + 1)
    top = keys.agg(F.max("k").alias("top"))
    ring = ring.crossJoin(F.broadcast(top)).select((F.col("k") - BUCKET).alias("fb"), (F.coalesce("next", "top") - BUCKET).alias("nb"))
    follow = ring.join(heads.withColumnRenamed("b", "hb"), F.col("nb") == F.col("hb")).select("fb", "head")
    return inside.join(follow, F.col("b") == F.col("fb"), "left").select("doc_id", text, *carry, F.coalesce(F.col("inner")[text], "head").alias(out), *[F.col("inner")[c].alias(f"next_{c}") for c in carry])


def fingerprints(docs: DataFrame) -> DataFrame:
    """The digest of the registered query: fingerprints of each text, of its edited text, and their likeness."""
    n = F.length("text")
    half = F.floor(n / 2).cast("int")
    own = with_fingerprint(docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")))
    rows = with_next(own, carry=("fingerprint",)).withColumn("edited", F.concat(F.substring("text", 1, n - half), F.substring("next_text", 1, half)))
    rows = with_fingerprint(rows, "edited", "edited_fingerprint")
    # Only the last row of a bucket has to work out its follower's.
    rows = rows.withColumn("next_fingerprint", F.coalesce("next_fingerprint", fingerprint_of(tree(F.col("next_text")))))
    return rows.select(
        "doc_id", n.cast("long").alias("n_chars"), F.sha2("edited", 256).alias("edited_sha256"), "fingerprint", "edited_fingerprint",
        likeness(F.col("fingerprint"), F.col("edited_fingerprint")).alias("near_edited"), likeness(F.col("fingerprint"), F.col("next_fingerprint")).alias("near_next"),
    )
