"""Repeated passages by merging Burrows-Wheeler transforms of shards.

A byte is removed if a LENGTH-byte string that covers it starts anywhere else as well.  Two equal strings have the same
leftmost smallest hash of SEED_BYTES bytes, at the same place within them.  So every start of a string belongs to one
occurrence of a seed, neighbouring starts with one seed form a context (their bytes, LENGTH - 1 bytes beyond the last
start included), and equal strings meet wherever contexts of equal seeds meet.  Contexts are dealt by seed; each start
is in exactly one context, so nothing is compared with itself and nothing is missed.

A reading task holds some megabytes of text at a time.  Of equal contexts among them one is dealt and all are reported,
as all their strings repeat; so a line that every text holds, or a long run of one byte, is dealt once for each such
portion, not once for each place.  A longer text is read in portions that share LENGTH - 1 bytes.

A task gets, from each portion, a shard of contexts.  Seeds that occur once are done with; equal contexts are one
with a count, and more than one of them means that all their strings repeat.  Of what is left every shard gets its own
suffix order and transform (one doubling sort of a small piece of text), and the shards' transforms are merged: the
interleave of all shards, at first one shard behind the other, is refined by stable passes over the preceding symbols,
each of which makes it right for two symbols more.  Bounds between neighbours appear at the pass in which their common
prefix ends; the intervals between bounds that hold more than one string after LENGTH symbols are the repeats.  No
suffix of the whole is sorted again.

Equal strings of two contexts have one seed; strings that are equal in spite of different seeds do not occur, so the
contexts of all seeds of a task are merged at once.

Null and empty texts, and those shorter than LENGTH bytes, lose nothing; an empty table gives an empty result.  Texts
are taken as UTF-8.  Rows are told apart by doc_id, null included, and 64 bits of their text's hash; rows equal in both
have one text and lose the same bytes, all of those that are covered.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import arrow_map, fresh

LENGTH, SEED_BYTES = 200, 32
MARK = 0xFF
FLUSH_BYTES = 6_000_000
#: Bytes of contexts that are merged at once.
MERGE_BYTES = 1_000_000
#: Bytes of text whose contexts one task gets, about a fourth of the contexts' bytes.
TASK_BYTES = 6_000_000
_MIX = np.random.default_rng(20240).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def seed_hashes(text: np.ndarray, width: int) -> np.ndarray:
    """A hash of the ``width`` bytes (a power of two) from each place on; the last width - 1 places have none."""
    h, size, factor = _MIX[text], 1, np.uint64(0x9E3779B97F4A7C15)
    while size < width:
        h = h[:-size] * factor + h[size:]
        factor = np.uint64((int(factor) ** 2 + 2) & (1 << 64) - 1)
        size *= 2
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def leftmost_smallest(h: np.ndarray, span: int) -> np.ndarray:
    """For each place, the leftmost place of the smallest of the ``span`` hashes from there on."""
    at, size = np.arange(len(h), dtype=np.int64), 1
    low = h
    while 2 * size <= span:
        take = low[size:] < low[:-size]
        at, low = np.where(take, at[size:], at[:-size]), np.minimum(low[:-size], low[size:])
        size *= 2
    if (rest := span - size) > 0:
        take = low[rest:] < low[:-rest]
        at = np.where(take, at[rest:], at[:-rest])
    return at


def contexts_of(texts: list[bytes], length: int = LENGTH, width: int = SEED_BYTES):
    """Of all texts: the joined bytes, and of each context its seed, text, first start (in the text), number of starts,
    and first byte (in the joined bytes)."""
    sizes = np.array([len(t) for t in texts], np.int64)
    first = np.cumsum(sizes) - sizes
    flat = np.frombuffer(b"".join(texts), np.uint8)
    if len(flat) < length:
        none = np.zeros(0, np.int64)
        return flat, none.astype(np.uint64), none, none, none, none
    h = seed_hashes(flat, width)
    p = leftmost_smallest(h, length - width + 1)
    owner = np.repeat(np.arange(len(texts)), sizes)[: len(p)]
    start = np.arange(len(p))
    ok = start + length <= (first + sizes)[owner]
    new = np.r_[True, (p[1:] != p[:-1]) | (owner[1:] != owner[:-1])] & ok
    new[1:] |= ok[1:] & ~ok[:-1]
    lo = np.flatnonzero(new)
    count = np.add.reduceat(ok.astype(np.int64), lo) if len(lo) else np.zeros(0, np.int64)
    return flat, h[p[lo]], owner[lo], lo - first[owner[lo]], count, lo


def doubling_order(symbols: np.ndarray, depth: int) -> np.ndarray:
    """Order of all suffixes of one shard by their first ``depth`` symbols (further ones may or may not count)."""
    rank, size, n = symbols.astype(np.int64), 1, len(symbols)
    order = np.argsort(symbols)
    while size < depth:
        after = np.full(n, -1, np.int64)
        after[: n - size] = rank[size:]
        key = rank * (max(n, 260) + 1) + after + 1
        order = np.argsort(key)
        k = key[order]
        new = np.r_[0, np.cumsum(k[1:] != k[:-1])]
        rank[order] = new
        size *= 2
        if new[-1] == n - 1:
            break
    return order


class Shard:
    """A text of contexts, each closed by a mark that UTF-8 has no byte for; its suffix order and its transform.

    The transform holds the two symbols before each suffix, and where in the order the suffix two symbols longer is.
    """

    def __init__(self, contexts: list[tuple[np.ndarray, int]], length: int):
        self.text = np.concatenate([np.r_[b, np.uint8(MARK)] for b, _ in contexts])
        self.order = doubling_order(self.text, length)
        row = np.empty(len(self.order), np.int32)
        row[self.order] = np.arange(len(self.order), dtype=np.int32)
        self.transform = self.text[self.order - 2].astype(np.uint16) << 8 | self.text[self.order - 1]
        self.longer = row[self.order - 2]
        sizes, starts = np.array([len(b) + 1 for b, _ in contexts]), np.array([k for _, k in contexts])
        self.base = np.cumsum(sizes) - sizes
        # The rows of the suffixes that begin where a string of a start ends.
        self.context = np.repeat(np.arange(len(contexts)), starts)
        within = np.arange(starts.sum()) - np.repeat(np.cumsum(starts) - starts, starts)
        self.rows = row[self.base[self.context] + within + length]


def repeated_intervals(shards: list[Shard], length: int) -> tuple[np.ndarray, np.ndarray]:
    """Rows (numbered through all shards) of the strings that repeat, and the interval each is in.

    The interleave begins with one shard behind the other, all in one interval: right for no symbol.  A pass puts the
    rows in order of the two symbols before them, without changing the order of those that agree, and goes on to the
    rows of the longer suffixes: right for two symbols more.  An interval ends where the symbols or the intervals of two
    neighbours differ.  A row alone in its interval can have no equal any more and is left out of further passes.
    """
    sizes = np.array([len(x.order) for x in shards])
    offset = np.cumsum(sizes) - sizes
    transform = np.concatenate([x.transform for x in shards])
    longer = np.concatenate([x.longer + o for x, o in zip(shards, offset, strict=True)])
    rows = np.concatenate([x.rows + o for x, o in zip(shards, offset, strict=True)])
    interval = np.zeros(len(rows), np.int64)
    for _ in range(length // 2):
        if not len(rows):
            break
        symbol = transform[rows]
        # Equal intervals lie together and must stay so: order by symbol first, then by the interval they were in.
        order = np.argsort(symbol, kind="stable")
        symbol, old = symbol[order], interval[order]
        bound = np.r_[True, (symbol[1:] != symbol[:-1]) | (old[1:] != old[:-1]), True]
        alone = bound[:-1] & bound[1:]
        interval = np.cumsum(bound[:-1])[~alone]
        rows = longer[rows[order[~alone]]]
    return rows, interval


def repeated_starts(shards: list[list[tuple[np.ndarray, int]]], length: int = LENGTH) -> list[list[np.ndarray]]:
    """Which starts of each context have an equal string elsewhere.  A shard is a list of (bytes, number of starts)."""
    if length % 2:
        raise ValueError("the length of a string must be even")
    built = [Shard(x, length) for x in shards]
    rows, _ = repeated_intervals(built, length)
    out = [[np.zeros(k, bool) for _, k in x] for x in shards]
    offset = np.cumsum([0, *[len(x.order) for x in built]])
    for i, x in enumerate(built):
        at = x.order[rows[(rows >= offset[i]) & (rows < offset[i + 1])] - offset[i]]
        ctx = np.searchsorted(x.base, at, side="right") - 1
        for c, start in zip(ctx.tolist(), (at - x.base[ctx]).tolist(), strict=True):
            out[i][c][start] = True
    return out


def _spans(mask: np.ndarray, offset: int, length: int) -> list[tuple[int, int]]:
    """Byte ranges of runs of repeated starts."""
    edge = np.flatnonzero(np.diff(np.r_[0, mask.astype(np.int8), 0]))
    return [(offset + int(a), offset + int(b) - 1 + length) for a, b in zip(edge[::2], edge[1::2], strict=True)]


def row_key(text: str = "text"):
    """A text's hash: tells rows of one doc_id apart."""
    return F.xxhash64(text)


def equals(flat: np.ndarray, at: np.ndarray, wide: np.ndarray, length: int, room: int = 1 << 22) -> np.ndarray:
    """For each context (first byte, number of bytes) the first one that is equal to it.

    Found by hashes of four stretches that cover it together, then compared byte by byte, ``room`` bytes at a time.
    """
    if not len(at):
        return at
    block = 1 << (length.bit_length() - 1)
    h, key = seed_hashes(flat, block), wide.astype(np.uint64)
    for j in range(4):
        key = (key * np.uint64(0x9E3779B97F4A7C15) ^ h[at + (wide - block) * j // 3]) * np.uint64(0xBF58476D1CE4E5B9)
        key ^= key >> np.uint64(31)
    _, index, inverse = np.unique(key, return_index=True, return_inverse=True)
    first = index[inverse]
    again = np.flatnonzero(first != np.arange(len(at)))
    for part in np.array_split(again, max(1, int(wide[again].sum()) // room)):
        same = wide[part] == wide[first[part]]
        first[part[~same]] = part[~same]
        part = part[same]
        if len(part):
            ends = np.cumsum(wide[part])
            within = np.arange(ends[-1]) - np.repeat(ends - wide[part], wide[part])
            equal = flat[np.repeat(at[part], wide[part]) + within] == flat[np.repeat(at[first[part]], wide[part]) + within]
            other = part[~np.logical_and.reduceat(equal, ends - wide[part])]
            first[other] = other
    return first


def pack_meta(seed: np.ndarray, ids: np.ndarray, keys: np.ndarray, start: np.ndarray, count: np.ndarray) -> bytes:
    """Columns one behind the other, in few bytes.  Of a seed 32 bits do: contexts that share them by chance are merely
    compared for nothing."""
    low = (seed >> np.uint64(32)).astype(np.uint32)
    return b"".join([low.tobytes(), np.diff(ids, prepend=np.int64(0)).tobytes(), keys.tobytes(), start.astype(np.uint32).tobytes(), count.astype(np.uint32).tobytes()])


def unpack_meta(data: bytes) -> np.ndarray:
    """Rows: seed, doc_id, row_key, first start, number of starts."""
    n = len(data) // 28
    parts = np.split(np.frombuffer(data, np.uint8), np.cumsum([4 * n, 8 * n, 8 * n, 4 * n]))
    kinds = (np.uint32, np.int64, np.int64, np.uint32, np.uint32)
    seed, ids, keys, start, count = (p.view(k).astype(np.int64) for p, k in zip(parts, kinds, strict=True))
    return np.stack([seed, np.cumsum(ids), keys, start, count])


def deal(docs: DataFrame, buckets: int, length: int = LENGTH) -> DataFrame:
    """bucket, meta, data: the contexts of each portion, by bucket of their seed; and, without data, the runs that equal
    contexts of a portion cover (as doc_id, row_key, start, number of bytes), in any bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        pack = zstandard.ZstdCompressor(level=3)
        held: list[tuple] = []
        size, turn = 0, TaskContext.get().partitionId()

        def row(bucket: int, meta: bytes, data: bytes | None) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([bucket], pa.int64()), pa.array([pack.compress(meta)], pa.binary()), pa.array([data], pa.binary())], names=["bucket", "meta", "data"])

        def flush():
            flat, seed, owner, start, count, at = contexts_of([h[2] for h in held], length)
            if not len(at):
                return
            ids, keys, offset = (np.array([h[i] for h in held], np.int64)[owner] for i in (0, 1, 3))
            start, wide = start + offset, count + length - 1
            first = equals(flat, at, wide, length)
            mine = first == np.arange(len(at))
            known = np.flatnonzero(np.isin(first, first[~mine]))
            if len(known):
                # Contexts lie in order of their starts, and so of their ends.
                a, e, o = start[known], (start + wide)[known], owner[known]
                new = np.flatnonzero(np.r_[True, (o[1:] != o[:-1]) | (a[1:] > e[:-1])])
                last = np.r_[new[1:], len(known)] - 1
                at_run = known[new]
                yield row(turn % buckets, pack_meta(seed[at_run], ids[at_run], keys[at_run], a[new], e[last] - a[new]), None)
            bucket = (seed >> np.uint64(1)) % np.uint64(buckets)  # smallest hashes crowd the low numbers: the rest of the division does not
            by = np.flatnonzero(mine)
            by = by[np.argsort(bucket[by], kind="stable")]
            cuts = np.flatnonzero(bucket[by][1:] != bucket[by][:-1]) + 1
            for some in np.split(by, cuts):
                ends = np.cumsum(wide[some])
                byte = flat[np.repeat(at[some] - (ends - wide[some]), wide[some]) + np.arange(ends[-1])]
                yield row(int(bucket[some[0]]), pack_meta(seed[some], ids[some], keys[some], start[some], count[some]), pack.compress(byte.tobytes()))

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                for i, k, t in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    if t is None or len(data := t.encode("utf-8", "surrogatepass")) < length:
                        continue
                    for begin in range(0, len(data) - length + 1, FLUSH_BYTES):
                        held.append((NO_ID if i is None else i, k, data[begin : begin + FLUSH_BYTES + length - 1], begin))
                        size += len(held[-1][2])
                        if size >= FLUSH_BYTES:
                            yield from flush()
                            held, size, turn = [], 0, turn + 7919
        if held:
            yield from flush()

    return docs.select("doc_id", row_key().alias("row_key"), "text").mapInArrow(run, "bucket long, meta binary, data binary")


#: Stands for a null doc_id among numbers.
NO_ID = -(1 << 63)


def resolve(shards: list[tuple[np.ndarray, np.ndarray]], length: int = LENGTH) -> Iterator[tuple[int, int, int, int]]:
    """(doc_id, row_key, start, end) of the repeated byte ranges of one bucket.  A shard is (meta, bytes)."""
    meta = np.concatenate([m for m, _ in shards], axis=1)
    shard_of = np.repeat(np.arange(len(shards)), [m.shape[1] for m, _ in shards])
    seed, ids, keys, start, count = meta
    wide = count + length - 1
    inner = np.concatenate([np.cumsum(m[4] + length - 1) - (m[4] + length - 1) for m, _ in shards])
    order = np.argsort(seed, kind="stable")
    same = seed[order][1:] == seed[order][:-1]
    many = np.zeros(len(seed), bool)
    many[order[1:][same]] = many[order[:-1][same]] = True
    # Equal contexts become one with a count.
    first: dict[tuple, list[int]] = {}
    for i in order[many[order]].tolist():
        b = shards[shard_of[i]][1][inner[i] : inner[i] + wide[i]]
        first.setdefault((int(seed[i]), xxhash.xxh3_128_digest(b)), []).append(i)
    by_seed: dict[int, list[list[int]]] = {}
    for (s, _), members in first.items():
        by_seed.setdefault(s, []).append(members)
    left: dict[int, list[tuple[int, int]]] = {}
    size = 0

    def merged() -> Iterator[tuple[int, int, int, int]]:
        """Merge what has gathered and give the ranges of contexts that stand alone."""
        work = [[(shards[s][1][inner[i] : inner[i] + wide[i]], int(count[i])) for i, _ in rows] for s, rows in left.items()]
        for rows, masks in zip(left.values(), repeated_starts(work, length), strict=True):
            for (i, n), mask in zip(rows, masks, strict=True):
                if n == 1:
                    for a, b in _spans(mask, int(start[i]), length):
                        yield int(ids[i]), int(keys[i]), a, b

    for kinds in by_seed.values():
        for members in kinds:
            if len(members) > 1:
                for i in members:
                    yield int(ids[i]), int(keys[i]), int(start[i]), int(start[i] + wide[i])
        if len(kinds) > 1:
            # Seeds never match one another, so a bucket is merged in portions of whole seeds.
            for members in kinds:
                i = members[0]
                left.setdefault(int(shard_of[i]), []).append((i, len(members)))
                size += int(wide[i])
            if size >= MERGE_BYTES:
                yield from merged()
                left, size = {}, 0
    if left:
        yield from merged()


def repeats(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, row_key, start, end: byte ranges of repeated strings; they may overlap."""
    total = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    buckets = max(8, -(-total // TASK_BYTES))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        unpack = zstandard.ZstdDecompressor()
        by_bucket: dict[int, list] = {}
        for batch in batches:
            for b, m, d in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                by_bucket.setdefault(b, []).append((m, d))
        for b in list(by_bucket):
            got = [(unpack_meta(unpack.decompress(m)), d) for m, d in by_bucket.pop(b)]
            shards = [(m, np.frombuffer(unpack.decompress(d), np.uint8)) for m, d in got if d is not None]
            rows = [r for m, d in got if d is None for r in zip(m[1].tolist(), m[2].tolist(), m[3].tolist(), (m[3] + m[4]).tolist(), strict=True)]
            rows += resolve(shards, length) if shards else []
            if rows:
                i, k, a, e = zip(*rows, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array([None if x == NO_ID else x for x in i], pa.int64()), pa.array(k), pa.array(a), pa.array(e)], names=["doc_id", "row_key", "start", "end"])

    return deal(docs, buckets, length).repartition(buckets, "bucket").mapInArrow(run, "doc_id long, row_key long, start long, end long")


def spans(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """doc_id, row_key, spans (sorted, possibly overlapping array of start, end) of texts with repeats."""
    return repeats(docs, length).groupBy("doc_id", "row_key").agg(F.sort_array(F.collect_set(F.struct("start", "end"))).alias("spans"))


def cut_out(data: bytes, ranges) -> tuple[bytes, int, int]:
    """(what is left, bytes removed, maximal runs removed)."""
    kept, at, gone, runs = [], 0, 0, 0
    last = -1
    for a, b in sorted(ranges):
        if a > last:
            runs += 1
        if b > at:
            kept.append(data[at : max(at, a)])
            gone += b - max(at, a)
            at = b
        last = max(last, b)
    kept.append(data[at:])
    return b"".join(kept), gone, runs


def remove(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """``docs`` with the repeated bytes removed from text; a character cut apart is dropped.  All columns stay."""
    import pandas as pd

    def run(texts: pd.Series, ranges: pd.Series) -> pd.Series:
        return pd.Series([t if r is None or t is None else cut_out(t.encode("utf-8"), [(x["start"], x["end"]) for x in r])[0].decode("utf-8", "ignore") for t, r in zip(texts, ranges, strict=True)])

    run.__annotations__ = {"texts": pd.Series, "ranges": pd.Series, "return": pd.Series}
    ident, key, ranges = fresh(docs, "_id", "_key", "_spans")
    found = spans(docs, length).select(F.col("doc_id").alias(ident), F.col("row_key").alias(key), F.col("spans").alias(ranges))
    joined = docs.join(found, docs["doc_id"].eqNullSafe(F.col(ident)) & (F.xxhash64(docs["text"]) == F.col(key)), "left")
    return joined.withColumn("text", F.pandas_udf(run, "string")(F.col("text"), F.col(ranges))).select(*[F.col(f"`{c}`") for c in docs.columns])


def summary(docs: DataFrame, length: int = LENGTH) -> DataFrame:
    """The digest of the registered query."""
    from hashlib import sha256

    def make():
        import zstandard

        unpack = zstandard.ZstdDecompressor()

        def kernel(cols):
            ids, texts, starts, ends = cols
            out = [ids, [], [], [], []]
            for t, a, b in zip(texts, starts, ends, strict=True):
                data = unpack.decompress(t)
                kept, gone, runs = cut_out(data, zip(a or (), b or (), strict=True))
                for c, v in zip(out[1:], (len(data), gone, runs, sha256(kept).hexdigest()), strict=True):
                    c.append(v)
            return out

        return kernel

    # Texts travel to their spans compressed one by one.
    packed = arrow_map(docs.select("doc_id", row_key().alias("row_key"), "text"), _squeezer, "doc_id long, row_key long, packed binary")
    found = spans(docs, length).select(F.col("doc_id").alias("_id"), F.col("row_key").alias("_key"), "spans")
    rows = packed.join(found, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("row_key") == F.col("_key")), "left")
    rows = rows.select("doc_id", "packed", F.col("spans.start").cast("array<int>").alias("starts"), F.col("spans.end").cast("array<int>").alias("ends"))
    return arrow_map(rows, make, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def _squeezer():
    import zstandard

    pack = zstandard.ZstdCompressor(level=3)
    return lambda cols: [cols[0], cols[1], [pack.compress((t or "").encode("utf-8", "surrogatepass")) for t in cols[2]]]
