"""SimHash near-duplicates, linked by a self-join of a binary trie over the fingerprints.

The trie is traversed by pairs of nodes.  A pair carries the number of bits in which the paths of its two nodes differ
and is dropped once that is over the budget; children are paired again until both nodes hold a few fingerprints, which
are then compared outright.  A level of the traversal is a handful of array operations over all pairs alive.

Which pairs meet in one task: of two fingerprints that differ in ``budget`` bits at most, one of ``budget + 1`` blocks
of bits agrees.  So each distinct fingerprint goes to one task for each block, under the block's value, and the
traversal goes on below that block.  A value with more than HOT fingerprints is divided again, into pairs of subtrees
of SPLIT_BITS more levels; a fingerprint then goes to each pair of its subtree that is within the budget.

Only the links a component needs are kept: neighbours in sorted order are linked first, and a pair of nodes whose
fingerprints are all in one component by then is dropped.  A group of near copies so costs about as many steps as it
has members, not their square; equal fingerprints are one node from the start.

Null and empty texts have no words and get fingerprint zero, which links like any other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import arrow_map, cut, fresh, partitions_of
from .components import components, local_components

BITS, BUDGET, SHINGLE, SEED = 64, 3, 3, 42
HOT, SPLIT_BITS = 200_000, 6
#: Node pairs with so few pairs of fingerprints are compared outright.
FEW = 16


def shingle_hashes(text: str | None, size: int = SHINGLE, seed: int = SEED) -> list[int]:
    """XXH64 of each shingle; A-Z are lower-cased and words end at ASCII white space, as bytes do it."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return []
    h = xxhash.xxh64_intdigest
    if len(words) < size:
        return [h(b" ".join(words), seed)]
    return [h(b" ".join(s), seed) for s in zip(*(words[i:] for i in range(size)), strict=False)]


def fingerprint(hashes: list[int] | np.ndarray) -> np.uint64:
    """The bits that are set in more than half of the hashes; zero without any."""
    if not len(hashes):
        return np.uint64(0)
    bits = np.unpackbits(np.asarray(hashes, np.uint64).astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
    return np.packbits(2 * bits.sum(axis=0, dtype=np.int64) > len(hashes)).view(">u8")[0]


def fingerprints_of(texts: list[str | None], size: int = SHINGLE) -> np.ndarray:
    """Unsigned 64-bit fingerprints: a bit is set if it is in more than half of the hashes."""
    out = np.zeros(len(texts), np.uint64)
    for i, t in enumerate(texts):
        out[i] = fingerprint(shingle_hashes(t, size))
    return out


def with_fingerprint(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """doc_id, th (hash of the text), fp (the 64 bits as a long) of every row."""

    def make():
        return lambda cols: [cols[0], cols[2], fingerprints_of(cols[1], size).view(np.int64).tolist()]

    return arrow_map(docs.select("doc_id", "text", F.xxhash64("text")), make, "doc_id long, th long, fp long")


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)


def trie_links(group: np.ndarray, code: np.ndarray, side: np.ndarray, bits: int, full: np.ndarray, budget: int) -> np.ndarray:
    """Component label of each row, from the links within each group.

    Rows are sorted by (group, code); ``code`` holds the ``bits`` levels of the trie, ``full`` the fingerprints.
    ``side``: 0 where a group is joined with itself, else 1 or 2, the two subtrees of a divided group, in this order.
    """
    n = len(code)
    cut_ = np.flatnonzero(np.r_[True, (group[1:] != group[:-1]) | (side[1:] != side[:-1]), True]) if n else np.zeros(1, int)
    lo, hi = cut_[:-1], cut_[1:]
    near = np.flatnonzero((group[1:] == group[:-1]) & (popcount(full[1:] ^ full[:-1]) <= budget)) if n > 1 else np.zeros(0, int)
    label = local_components(n, near, near + 1)
    first = side[lo] if n else np.zeros(0, int)
    own, left = first == 0, np.flatnonzero(first == 1)
    right = left + 1
    ok = (right < len(lo)) & (group[lo[np.minimum(right, len(lo) - 1)]] == group[lo[left]]) if len(left) else np.zeros(0, bool)
    left, right = left[ok], right[ok]
    al, ah, bl, bh = np.r_[lo[own], lo[left]], np.r_[hi[own], hi[left]], np.r_[lo[own], lo[right]], np.r_[hi[own], hi[right]]
    diff = np.zeros(len(al), np.int64)
    for level in range(bits - 1, -2, -1):
        # Pairs of few are compared; those of one component are done with.
        keep = np.where(al == bl, ah - al > 1, True)
        al, ah, bl, bh, diff = (x[keep] for x in (al, ah, bl, bh, diff))
        if not len(al):
            break
        few = ((ah - al) * (bh - bl) <= FEW) | (level < 0)
        if few.any():
            i, j = _pairs(al[few], ah[few], bl[few], bh[few])
            hit = popcount(full[i] ^ full[j]) <= budget
            label = local_components(n, i[hit], j[hit], label)
            al, ah, bl, bh, diff = (x[~few] for x in (al, ah, bl, bh, diff))
        if not len(al):
            break
        one = _one_component(label, al, ah, bl, bh)
        al, ah, bl, bh, diff = (x[~one] for x in (al, ah, bl, bh, diff))
        if not len(al):
            break
        # Descend: the ones of a node's bit stand at its end.
        ones = np.r_[0, np.cumsum((code >> np.uint64(level)) & np.uint64(1), dtype=np.int64)]
        am, bm = ah - (ones[ah] - ones[al]), bh - (ones[bh] - ones[bl])
        cross = al != bl
        al, ah, bl, bh, diff = (np.concatenate(x) for x in zip(
            (al, am, bl, bm, diff), (am, ah, bm, bh, diff), (al, am, bm, bh, diff + 1), (am[cross], ah[cross], bl[cross], bm[cross], diff[cross] + 1), strict=True))
        keep = (diff <= budget) & (al < ah) & (bl < bh)
        al, ah, bl, bh, diff = (x[keep] for x in (al, ah, bl, bh, diff))
    return label


def _pairs(al: np.ndarray, ah: np.ndarray, bl: np.ndarray, bh: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All index pairs of the ranges, i < j where a range is paired with itself."""
    wide = bh - bl
    count = (ah - al) * wide
    at = np.repeat(np.arange(len(al)), count)
    k = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
    i, j = al[at] + k // wide[at], bl[at] + k % wide[at]
    keep = i < j
    return i[keep], j[keep]


def _one_component(label: np.ndarray, al, ah, bl, bh) -> np.ndarray:
    """Pairs of nodes whose rows all have one label: the label changes nowhere within either, and the two agree."""
    change = np.r_[0, np.cumsum(label[1:] != label[:-1]), 0]
    return (change[ah - 1] == change[al]) & (change[bh - 1] == change[bl]) & (label[al] == label[bl])


def links(fps: DataFrame, budget: int = BUDGET, hot: int = HOT) -> DataFrame:
    """a, b: links that span the components of distinct fingerprints ``fps`` (column fp)."""
    blocks = budget + 1
    width = BITS // blocks
    rest = BITS - width

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            for r in range(blocks):
                turned = _turn(fp.view(np.uint64), r * width)
                key = np.uint64(r << width) | (turned >> np.uint64(rest))
                yield pa.RecordBatch.from_arrays([pa.array(key.astype(np.int64)), pa.array(fp)], names=["key", "fp"])

    dealt = fps.select("fp").mapInArrow(deal, "key long, fp long")
    full = dealt.groupBy("key").agg(F.count("*").alias("n")).filter(F.col("n") > hot).select(F.col("key").alias("hot_key"))
    marked = dealt.join(full, F.col("key") == F.col("hot_key"), "left").select("key", "fp", F.col("hot_key").isNotNull().alias("hot"))
    mask = (1 << SPLIT_BITS) - 1

    def divide(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of hot keys go to every pair of subtrees within the budget; others stay."""
        mates = [[q for q in range(mask + 1) if (p ^ q).bit_count() <= budget] for p in range(mask + 1)]
        for batch in batches:
            key, fp, is_hot = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            keys, fs, sides = [key[~is_hot] << (2 * SPLIT_BITS)], [fp[~is_hot]], [np.zeros((~is_hot).sum(), np.int64)]
            if is_hot.any():
                key, fp = key[is_hot], fp[is_hot]
                r = (key >> width).astype(np.int64)
                head = np.array([(int(_turn(np.array([f]).view(np.uint64), int(k) * width)[0]) >> (rest - SPLIT_BITS)) & mask for f, k in zip(fp, r, strict=True)])
                for p in np.unique(head):
                    mine = head == p
                    for q in mates[p]:
                        u, v = min(p, q), max(p, q)
                        keys.append(key[mine] << (2 * SPLIT_BITS) | (u << SPLIT_BITS) | v)
                        fs.append(fp[mine])
                        sides.append(np.full(mine.sum(), 0 if u == v else 1 if p == u else 2, np.int64))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (keys, fs, sides)], names=["key", "fp", "side"])

    def join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b for b in batches if b.num_rows]
        if not got:
            return
        key, fp, side = (np.concatenate([b.column(i).to_numpy(zero_copy_only=False) for b in got]) for i in range(3))
        turn = (key >> (2 * SPLIT_BITS + width)).astype(np.int64)
        code = np.zeros(len(fp), np.uint64)
        for r in range(blocks):
            code[turn == r] = _turn(fp[turn == r].view(np.uint64), r * width)
        code &= np.uint64((1 << rest) - 1)
        # Two keys of one block value never share a task by chance only: the key is part of the group.
        order = np.lexsort((code, side, key))
        key, fp, side, code = key[order], fp[order], side[order], code[order]
        label = trie_links(key, code, side, rest, fp.view(np.uint64), budget)
        at = np.flatnonzero(label != np.arange(len(label)))
        yield pa.RecordBatch.from_arrays([pa.array(fp[at]), pa.array(fp[label[at]])], names=["a", "b"])

    tasks = partitions_of(fps.sparkSession)
    return marked.mapInArrow(divide, "key long, fp long, side long").repartition(tasks, "key").mapInArrow(join, "a long, b long")


def _turn(fp: np.ndarray, by: int) -> np.ndarray:
    """Bits turned left."""
    by %= BITS
    return fp if not by else (fp << np.uint64(by)) | (fp >> np.uint64(BITS - by))


def near_duplicates(docs: DataFrame, size: int = SHINGLE, budget: int = BUDGET, hot: int = HOT) -> DataFrame:
    """doc_id, th (hash of the text), fp, root (a fingerprint), component_id (smallest doc_id reachable over links) of every row."""
    marked = cut(with_fingerprint(docs, size))
    first = marked.groupBy("fp").agg(F.min("doc_id").alias("least"))
    linked = components(links(first.select("fp"), budget, hot))
    rooted = first.join(linked, F.col("fp") == F.col("node"), "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))
    ids = rooted.groupBy("root").agg(F.min("least").alias("component_id"))
    by_fp = rooted.join(ids, "root").select(F.col("fp").alias("_fp"), "root", "component_id")
    return marked.join(by_fp, F.col("fp") == F.col("_fp")).select("doc_id", "th", "fp", "root", "component_id")


def summary(docs: DataFrame) -> DataFrame:
    """The digest of the registered query.  Rows without a doc_id are rows like any other; a component of such rows alone has a null id."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def deduplicate(docs: DataFrame, size: int = SHINGLE, budget: int = BUDGET) -> DataFrame:
    """One document of each group; see ``keep_first``."""
    return keep_first(docs, near_duplicates(docs, size, budget))


def keep_first(docs: DataFrame, groups: DataFrame) -> DataFrame:
    """One row of each group: the smallest doc_id, those without one last; of different texts of one doc_id the one with
    the smallest hash; of rows equal in both any one.  All columns stay.

    ``groups`` has doc_id, th (xxhash64 of the text) and root (any name of the group) of every row.  Documents that go
    are looked up by id and text hash; only the keys of what goes and of rows that repeat travel, not the texts, where
    these keys are few enough to be broadcast.
    """
    from pyspark.sql import Window as W

    ident, text_hash, many, turn = fresh(docs, "_id", "_th", "_many", "_turn")
    rows = groups.groupBy("root", "doc_id", "th").agg(F.count("*").alias("n"))
    first = rows.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "th")).alias("f")).select(F.col("root").alias("_root"), "f")
    same = F.col("doc_id").eqNullSafe(F.col("f.doc_id")) & (F.col("th") == F.col("f.th"))
    marks = rows.join(first, F.col("root") == F.col("_root")).select(F.col("doc_id").alias(ident), F.col("th").alias(text_hash), same.alias("_first"), (F.col("n") > 1).alias(many))
    marks = cut(marks.filter(f"not _first or `{many}`").select(ident, text_hash, (F.col("_first") & F.col(many)).alias(many)))
    on = docs["doc_id"].eqNullSafe(F.col(ident)) & (F.xxhash64(docs["text"]) == F.col(text_hash))
    repeated = docs.join(marks.filter(F.col(many)), on, "left_semi")
    plain = [F.col(f"`{f.name}`") for f in docs.schema if "map<" not in f.dataType.simpleString()]  # maps have no hash
    w = W.partitionBy(F.col("doc_id"), F.xxhash64("text")).orderBy(F.xxhash64(*plain))
    one = repeated.withColumn(turn, F.row_number().over(w)).filter(F.col(turn) == 1).drop(turn)
    return docs.join(marks, on, "left_anti").unionByName(one)
