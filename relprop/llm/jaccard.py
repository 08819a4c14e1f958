"""Near copies by a trie of fingerprints, completed by Jaccard likeness of word shingles: every pair of LEAST or more is linked.

A text is the set of hashes of its SHINGLE-word shingles; texts of one set are one node.  The self-join of the binary trie
of ``simhash`` links nodes whose fingerprints (of the distinct shingles) differ in BUDGET bits at most; what it makes one
component is not compared again.  An exact check by a prefix filter then adds the pairs that lie further apart in bits.

Two sets of likeness 4/5 or
more share at least 4/5 of either, so in any fixed order of all shingles the first n - ceil(4n/5) + k of each have k in
common, the smaller k of the two (prefix filter).  These are a node's keys; k is 1 + n // EXTRA.  A node that has fewer
keys in common with others than any partner asks for drops out, and nodes that share keys are candidates; the likeness
of candidates is worked out on the whole sets.

The order decides on the cost alone, not on the result: shingles that are frequent in a sample of texts come last, so
a line that many texts hold is a key only of texts that hold little else.

A key of many nodes is not paired outright.  Its nodes are compared with one of them, the centre: one that has much in
common with others.  What is LEAST or more alike to the centre is one component.  The rest is told by what each node has
and the centre has not, or the other way round (its difference): two sets differ in exactly the symbols in which their
differences differ.  If x is less than LEAST alike to the centre, and y differs from it in b shingles, x and y are
alike only if they share more than about b/2 of these, so x has one of the first b/2 of y, in an order that has the shingles
foreign to the centre before its own.  Edits made apart seldom agree in a foreign shingle.  All pairs of a node of likeness NEAR to
the centre are so settled, and it leaves the key; the others go on with another centre.  Keys of few open pairs, and what is
left after ROUNDS, are paired outright.

Null and empty texts have no shingles and are one node, which links to no other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import SLICE_ROWS, arrow_map, cut, partitions_of
from .components import components
from .simhash import BUDGET, fingerprint, keep_first, shingle_hashes
from .simhash import links as trie_join

SHINGLE = 5
#: The least likeness, as a fraction.
LEAST = (4, 5)
#: A set of n shingles has n // EXTRA more keys than one shared key asks for.
EXTRA = 20
#: Texts in the sample that orders the shingles, texts of it that make a shingle frequent, frequent shingles told apart.
SAMPLE, FREQUENT, APART = 8_000, 5, 100_000
#: Rounds of comparisons with the centre of a key, at most; a key of at most ROOM open pairs for each of its nodes takes part in none.  They end early
#: once the other keys have no more open pairs than the first round had nodes of keys.
ROUNDS, ROOM = 4, 4
#: Nodes of this likeness to a centre, as a fraction, are settled with it.
NEAR = (1, 2)
#: Bytes of a hash in the sets that are compared as a whole.
WIDTH = 6
#: Slots of the filter that tells most texts without candidates.
SLOTS = 1 << 22
#: Slots of the filter that tells most shingles of differences that no other node of the centre has, as a power of two; bytes of a piece of it.
SLOT_BITS, PIECE = 22, 4096
#: Up to so many links one task works out the components.
FEW_LINKS = 1 << 20


def shingle_set(text: str | None, size: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes."""
    return np.unique(np.array(shingle_hashes(text, size), np.uint64))


def node_of(held: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(held.tobytes()) - (1 << 63)


def packed(held: np.ndarray) -> bytes:
    """The set by the leading WIDTH bytes of its hashes: two different ones of a few thousand agree once in a million pairs of sets."""
    x = np.unique(held >> np.uint64(64 - 8 * WIDTH))
    return np.ascontiguousarray(x.view(np.uint8).reshape(-1, 8)[:, :WIDTH]).tobytes()


def unpacked(data: bytes) -> np.ndarray:
    out = np.zeros((len(data) // WIDTH, 8), np.uint8)
    out[:, :WIDTH] = np.frombuffer(data, np.uint8).reshape(-1, WIDTH)
    return out.view(np.uint64).ravel()


def keys_of(held: np.ndarray, late: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The first shingles of a set, of which two sets of LEAST share 1 + n // EXTRA of the smaller set; ``late`` (sorted) come by rank at the end."""
    n, (p, q) = len(held), LEAST
    if not n:
        return held
    if len(late):
        at = np.minimum(np.searchsorted(late, held), len(late) - 1)
        held = held[np.lexsort((held, np.where(late[at] == held, rank[at] + 1, 0)))]
    return held[: n + (-p * n // q) + 1 + n // EXTRA]


def frequent(docs: DataFrame, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that are frequent in a sample of texts (sorted), and their rank by frequency."""
    every = max(1, docs.count() // SAMPLE)

    def make():
        return lambda cols: [[x for t in cols[0] for x in shingle_set(t, size).view(np.int64).tolist()]]

    some = docs.select("text").filter(F.pmod(F.xxhash64("text"), F.lit(every)) == 0)
    rows = arrow_map(some, make, "key long").groupBy("key").count().filter(F.col("count") >= FREQUENT).orderBy(F.desc("count"), "key").limit(APART).collect()
    keys = np.array([r[0] for r in rows], np.int64).view(np.uint64)
    order = np.argsort(keys)
    return keys[order], (len(rows) - order).astype(np.int64)


def with_keys(docs: DataFrame, late: np.ndarray, rank: np.ndarray, size: int = SHINGLE) -> DataFrame:
    """doc_id, node, n (shingles), keys, th (hash of the text), fp (fingerprint of the set) of every row."""

    def make():
        def kernel(cols):
            sets = [shingle_set(t, size) for t in cols[1]]
            return [cols[0], [node_of(s) for s in sets], [len(s) for s in sets], [keys_of(s, late, rank).view(np.int64).tolist() for s in sets], cols[2], np.array([fingerprint(s) for s in sets], np.uint64).view(np.int64).tolist()]

        return kernel

    return arrow_map(docs.select("doc_id", "text", F.xxhash64("text")), make, "doc_id long, node long, n long, keys array<long>, th long, fp long")


def trie_parts(marked: DataFrame, budget: int = BUDGET) -> DataFrame:
    """a, b: each node with the smallest node of its component in the trie, where that is another one."""
    nodes = marked.select("node", "fp").distinct()
    linked = components(trie_join(nodes.select("fp").distinct(), budget), FEW_LINKS).select(F.col("node").alias("_fp"), "root")
    rooted = nodes.join(linked, F.col("fp") == F.col("_fp"), "left").select("node", F.coalesce("root", "fp").alias("root"))
    least = rooted.groupBy("root").agg(F.min("node").alias("b")).withColumnRenamed("root", "_root")
    return rooted.join(least, F.col("root") == F.col("_root")).filter("node <> b").select(F.col("node").alias("a"), "b")


def shared(rows: DataFrame) -> DataFrame:
    """The distinct rows (key, node) of keys that more than one node has.

    Rows come sorted by key and node, so a task holds one batch of them, however many nodes a key has.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # The last row of the batch before: it goes out once its key is seen to be shared.
        key, node, out = np.zeros(0, np.int64), np.zeros(0, np.int64), False
        for batch in batches:
            k, m = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            key, node = np.r_[key, k], np.r_[node, m]
            if not len(key):
                continue
            new = np.r_[True, (key[1:] != key[:-1]) | (node[1:] != node[:-1])]
            key, node = key[new], node[new]
            same = key[1:] == key[:-1]
            keep = np.r_[out, same] | np.r_[same, False]
            keep[0] &= not out  # it went out before
            yield pa.RecordBatch.from_arrays([pa.array(key[keep]), pa.array(node[keep])], names=["key", "node"])
            out = bool(same[-1]) if len(same) else out
            key, node = key[-1:], node[-1:]

    return rows.repartition(partitions_of(rows.sparkSession), "key").sortWithinPartitions("key", "node").mapInArrow(run, "key long, node long")


def alike(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) of LEAST or more, of whole sets."""
    p, q = LEAST

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(at, SLICE_ROWS) for whole in batches for at in range(0, whole.num_rows, SLICE_ROWS)):
            a, b, x, y = (c.to_pylist() for c in batch.columns)
            keep = []
            for u, v in zip(x, y, strict=True):
                both = len(np.intersect1d(unpacked(u), unpacked(v), assume_unique=True))
                keep.append(q * both >= p * ((len(u) + len(v)) // WIDTH - both))
            yield pa.RecordBatch.from_arrays([pa.array([i for i, k in zip(c, keep, strict=True) if k], pa.int64()) for c in (a, b)], names=["a", "b"])

    left, right = (sets.select(F.col("node").alias(f"_{k}"), F.col("held").alias(f"held_{k}")) for k in "ab")
    both = pairs.join(left, F.col("a") == F.col("_a")).join(right, F.col("b") == F.col("_b"))
    return both.select("a", "b", "held_a", "held_b").mapInArrow(run, "a long, b long")


def _pairs(df: DataFrame, every_key: bool) -> DataFrame:
    """a < b of rows (x, n, y, m), one for each key a pair shares, whose sizes and keys allow for LEAST, each pair once."""
    p, q = LEAST
    fit = df.filter((F.col("n") * q >= F.col("m") * p) & (F.col("m") * q >= F.col("n") * p))
    pairs = fit.groupBy(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count("*").alias("c"), F.min(F.least("n", "m")).alias("n"))
    return (pairs.filter(F.col("c") > F.floor(F.col("n") / EXTRA)) if every_key else pairs).select("a", "b")


def difference(held: np.ndarray, centre: np.ndarray, late: np.ndarray, rank: np.ndarray) -> tuple[bool, bool, int, np.ndarray, np.ndarray]:
    """Is a set LEAST alike to the centre, is it NEAR; how many shingles differ, which it is found by, which it asks for.

    In order: shingles foreign to the centre by rank, then those the centre has alone, those of a rank (``late``, sorted) first.

    Let x and y differ from the centre r in a and b shingles, and x be less than LEAST = p/q alike to it.  Sets of n and m
    shingles are LEAST alike if they differ in w (n + m) at most, w = (q - p) / (q + p).  So a > w (n + |r|), and x and y
    share at least (a + b - w (n + m)) / 2 > (b + w (|r| - m)) / 2 shingles of their differences; the first shared one is among
    the first of y that leave room for so many.  x has at most w (n + m) <= n (q - p) / p of its own before it.  Where y is NEAR,
    a is at most w (n + m) plus the bound of b.
    """
    (p, q), (u, v), n, m = LEAST, NEAR, len(held), len(centre)
    own, lost = np.setdiff1d(held, centre, assume_unique=True), np.setdiff1d(centre, held, assume_unique=True)
    if len(late):
        at, gone = (np.minimum(np.searchsorted(late, x), len(late) - 1) for x in (own, lost))
        own = own[np.argsort(np.where(late[at] == own, rank[at] + 1, 0), kind="stable")]
        lost = lost[np.argsort(late[gone] != lost, kind="stable")]
    both, delta = n - len(own), np.concatenate([own, lost])
    like, near = q * both >= p * (n + m - both), v * both >= u * (n + m - both)
    none, d = delta[:0], len(delta)
    least = ((q + p) * d + (q - p) * (m - n)) // (2 * (q + p)) + 1
    far = (q - p) * n * (u + v) + (v - u) * (q * n + p * m)  # p (u + v) times the most that a partner of a near set differs
    asks = not like and d * p * (u + v) <= far
    return like, near, d, delta[: max(0, d - least + 1)] if near else none, delta[: n * (q - p) // p + 1] if asks else none


def around(groups: DataFrame, sets: DataFrame, late: np.ndarray, rank: np.ndarray) -> DataFrame:
    """r, node, n, part, alike, near, d, found_by, asks of the rows (r, node, part): each node and the centre r; see ``difference``."""
    late, first = np.unique(late >> np.uint64(64 - 8 * WIDTH), return_index=True)
    rank = rank[first]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(at, SLICE_ROWS) for whole in batches for at in range(0, whole.num_rows, SLICE_ROWS)):
            x, y = (batch.column(i).to_pylist() for i in (3, 4))
            told = [difference(unpacked(u), unpacked(v), late, rank) for u, v in zip(x, y, strict=True)]
            like, near = (pa.array([bool(d[i]) for d in told], pa.bool_()) for i in (0, 1))
            lists = [pa.array([d[i].view(np.int64) for d in told], pa.list_(pa.int64())) for i in (3, 4)]
            n, d = pa.array([len(u) // WIDTH for u in x], pa.int64()), pa.array([d[2] for d in told], pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), n, batch.column(2), like, near, d, *lists], names=["r", "node", "n", "part", "alike", "near", "d", "found_by", "asks"])

    left, right = (sets.select(F.col("node").alias(f"_{k}"), F.col("held").alias(f"held_{k}")) for k in "ab")
    both = groups.join(left, F.col("node") == F.col("_a")).join(right, F.col("r") == F.col("_b"))
    return both.select("r", "node", "part", "held_a", "held_b").mapInArrow(run, "r long, node long, n long, part long, alike boolean, near boolean, d long, found_by array<long>, asks array<long>")


def _in_parts(rows: DataFrame, roots: DataFrame) -> DataFrame:
    """Rows (key, node, n, score) with part, the root of the node's component."""
    return rows.join(roots.select(F.col("node").alias("_n"), "root"), F.col("node") == F.col("_n"), "left").select("key", "node", "n", "score", F.coalesce("root", "node").alias("part"))


def _still_open(rows: DataFrame) -> DataFrame:
    """The rows of keys whose nodes are not all in one component, with ``each``: the key's pairs of different components for each row of it."""
    parts = rows.groupBy("key", "part").agg(F.count("*").alias("c")).groupBy("key").agg(F.sum("c").alias("s"), F.sum(F.col("c") * F.col("c")).alias("w"))
    left = (F.col("s") * F.col("s") - F.col("w")) / 2
    still = parts.filter(left > 0).select(F.col("key").alias("_k"), (left / F.col("s")).alias("each"))
    return rows.join(still, F.col("key") == F.col("_k")).drop("_k")


def _slots(batch: pa.RecordBatch, column: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Row, place and value of each shingle in a list column, and the slot of it and the row's centre."""
    held, odd = batch.column(column), np.uint64(0x9E3779B97F4A7C15)
    size = pc.list_value_length(held).to_numpy(zero_copy_only=False).astype(np.int64)
    row, e = np.repeat(np.arange(len(size)), size), held.flatten().to_numpy(zero_copy_only=False)
    place = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
    r = batch.column("r").to_numpy(zero_copy_only=False).view(np.uint64)[row]
    return row, place, e, ((e.view(np.uint64) ^ (r * odd)) * odd) >> np.uint64(64 - SLOT_BITS)


def _taken(told: DataFrame) -> dict[str, np.ndarray]:
    """Of found_by and asks, the slots that any row takes, as bits."""
    names = ("found_by", "asks")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        taken = np.zeros((2, 1 << (SLOT_BITS - 3)), np.uint8)
        for batch in batches:
            for bits, name in zip(taken, names, strict=True):
                slot = np.unique(_slots(batch, name)[3])
                np.bitwise_or.at(bits, slot >> np.uint64(3), np.uint8(1) << (slot & np.uint64(7)).astype(np.uint8))
        pieces = taken.reshape(-1, PIECE)
        at = np.flatnonzero(pieces.any(axis=1))
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array([pieces[i].tobytes() for i in at], pa.binary())], names=["at", "bits"])

    out = np.zeros((2, 1 << (SLOT_BITS - 3)), np.uint8)
    for at, bits in told.select("r", *names).mapInArrow(run, "at long, bits binary").groupBy("at").agg(F.bitmap_or_agg("bits")).collect():
        out.reshape(-1, PIECE)[at] = np.frombuffer(bits, np.uint8)
    return dict(zip(names, out, strict=True))


def _spread(told: DataFrame, column: str, taken: np.ndarray, schema: str) -> DataFrame:
    """A row (r, node, n, part, d, place, shingle) for each shingle of a list column whose slot is taken; named as in ``schema``."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (whole.slice(at, SLICE_ROWS) for whole in batches for at in range(0, whole.num_rows, SLICE_ROWS)):
            row, place, e, slot = _slots(batch, column)
            keep = (taken[slot >> np.uint64(3)] >> (slot & np.uint64(7)).astype(np.uint8)) & 1 == 1
            yield pa.RecordBatch.from_arrays([*(c.take(pa.array(row[keep])) for c in batch.columns[:5]), pa.array(place[keep]), pa.array(e[keep])], names=names)

    return told.select("r", "node", "n", "part", "d", column).mapInArrow(run, schema)


def _met(told: DataFrame) -> DataFrame:
    """Rows x, n, y, m of different components that the differences leave open: x asks for a shingle that y is found by.

    Of the first shingle that two differences share, the place in either leaves room for as many as they have to share.
    Shingles that nothing else around the centre asks for, or is found by, make no row, but for those of a shared slot.
    """
    (p, q), taken = LEAST, _taken(told)
    asks = _spread(told, "asks", taken["found_by"], "r long, x long, n long, part long, a long, i long, e long")
    has = _spread(told, "found_by", taken["asks"], "_r long, y long, m long, _p long, b long, j long, _e long")
    least = (q + p) * (F.col("a") + F.col("b")) - (q - p) * (F.col("n") + F.col("m"))
    room = 2 * (q + p) * F.least(F.col("a") - F.col("i"), F.col("b") - F.col("j"))
    return asks.join(has, (F.col("r") == F.col("_r")) & (F.col("e") == F.col("_e")) & (F.col("x") != F.col("y")) & (F.col("part") != F.col("_p")) & (least <= room)).select("x", "n", "y", "m")


def links(open_: DataFrame, sets: DataFrame, known: DataFrame, late: np.ndarray, rank: np.ndarray) -> DataFrame:
    """a, b: links that span the components of the nodes of ``open_`` (key, node, n, score: high for a good centre), those of ``known`` (a, b: the least of a component) among them.

    A node leaves a key only when its pairs with all other nodes of the key are settled, so a pair that is not settled is
    paired outright under every key it shares, as the count of its keys asks for.
    """
    found, aside = known, None
    roots = known.select(F.col("a").alias("node"), F.col("b").alias("root"))
    rows, at_most, many = cut(_still_open(_in_parts(open_, roots))), 0, F.col("each") > ROOM
    for _ in range(ROUNDS):
        n, pairs = rows.filter(many).agg(F.count("*"), F.sum("each")).first()
        if not n or pairs <= at_most:
            break
        at_most = at_most or n
        few = rows.filter(~many).drop("part", "each")
        aside = few if aside is None else aside.unionByName(few)
        rows = rows.filter(many)
        best = rows.groupBy("key").agg(F.max(F.struct("score", F.col("node").alias("r"))).alias("o")).select(F.col("key").alias("_k"), F.col("o.r").alias("r"))
        rows = cut(rows.join(best, F.col("key") == F.col("_k")).filter("node <> r").select("key", "node", "n", "score", "part", "r"))
        told = cut(around(rows.select("r", "node", "part").distinct(), sets, late, rank))
        new = told.filter("alike and part <> r").select(F.col("node").alias("a"), F.col("r").alias("b")).unionByName(alike(_pairs(_met(told), False), sets))
        if not (new := cut(new)).isEmpty():
            found = cut(found.unionByName(new))
            roots = components(found, FEW_LINKS)
        settled = told.filter("near").select(F.col("r").alias("_r"), F.col("node").alias("_n"))
        rest = rows.join(settled, (F.col("r") == F.col("_r")) & (F.col("node") == F.col("_n")), "left_anti").select("key", "node", "n", "score")
        rows = cut(_still_open(_in_parts(rest, roots)))
        if settled.isEmpty():  # texts that share little else: no centre brings them together
            break
    rest = rows.select("key", "node", "n", "score")
    rows = cut(_still_open(_in_parts(rest if aside is None else aside.unionByName(rest), roots)).drop("each", "score"))
    other = rows.select(F.col("key").alias("_k"), F.col("node").alias("y"), F.col("n").alias("m"), F.col("part").alias("_p"))
    met = rows.withColumnRenamed("node", "x").join(other, (F.col("key") == F.col("_k")) & (F.col("x") < F.col("y")) & (F.col("part") != F.col("_p")))
    return cut(found.unionByName(alike(_pairs(met, True), sets)))


def near_copies(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """doc_id, th (hash of the text), node, root, component_id (smallest doc_id reachable over pairs of BUDGET bits or LEAST) of every row."""
    late, rank = frequent(docs, size)
    marked = cut(with_keys(docs, late, rank, size))
    met = cut(shared(marked.select(F.explode("keys").alias("key"), "node")))
    marked = cut(marked.drop("keys"))  # what held the keys goes
    known = cut(trie_parts(marked))
    about = marked.groupBy(F.col("node").alias("_n")).agg(F.first("n").alias("n"), F.min("th").alias("th"))
    p, q = LEAST
    least = F.floor(F.ceil(F.col("n") * p / q) / EXTRA) + 1  # of the smallest partner
    alive = met.groupBy("node").agg(F.count("*").alias("c")).join(about, F.col("node") == F.col("_n")).filter(F.col("c") >= least).select("_n", "n", "th", (F.col("c") / F.col("n")).alias("score"))
    open_ = cut(met.join(alive, F.col("node") == F.col("_n")).drop("_n"))
    del met, alive, about
    wanted = np.zeros(SLOTS, bool)
    wanted[open_.select(F.pmod("th", F.lit(SLOTS)).cast("int").alias("slot")).distinct().toArrow().column(0).to_numpy()] = True
    bits = np.packbits(wanted)

    def make():
        held = np.unpackbits(bits).view(bool)

        def kernel(cols):
            sets = [shingle_set(t, size) for t, at in zip(*cols, strict=True) if held[at]]
            return [[node_of(s) for s in sets], [packed(s) for s in sets]]

        return kernel

    sets = arrow_map(docs.select("text", F.pmod(F.xxhash64("text"), F.lit(SLOTS))), make, "node long, held binary")
    sets = cut(sets.join(open_.select(F.col("node").alias("_n")).distinct(), F.col("node") == F.col("_n"), "left_semi").groupBy("node").agg(F.first("held").alias("held")))
    linked = components(links(open_.drop("th"), sets, known, late, rank), FEW_LINKS)
    rooted = marked.groupBy("node").agg(F.min("doc_id").alias("least")).join(linked.withColumnRenamed("node", "_n"), F.col("node") == F.col("_n"), "left").select("node", "least", F.coalesce("root", "node").alias("root"))
    ids = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    by_node = rooted.join(ids, "root").select(F.col("node").alias("_node"), "root", "component_id")
    return marked.join(by_node, F.col("node") == F.col("_node")).select("doc_id", "th", "node", "root", "component_id")


def deduplicate(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """One document of each group of near copies; see ``keep_first``."""
    return keep_first(docs, near_copies(docs, size))
