"""Quality by perplexity under an interpolated modified Kneser-Ney model of characters, trained on trusted texts.

Texts are read once.  Each task packs its rows into blocks of BLOCK_CHARS characters and adds what the block has to ask
and to tell: its distinct n-grams, and how often each occurs in its trusted texts.  Everything after that is equi-joins
of distinct n-grams, sharded by n-gram: counts of each order, the sums of each context, the probabilities of every
n-gram that some block asked for.  The answers go back to where the blocks lie, and documents are scored there.  No model is
collected or broadcast; what is gathered grows with the blocks.

An n-gram is one long of ORDER symbols of 15 bits.  Code points below WIDE are symbols of their own; a higher one is a
pair of symbols that no other code point has.  Three start marks and an end mark belong to every text, so null and
empty texts have one symbol to predict.

Of the trusted documents, one in FOLDS (by the hash of its text, so that copies stay together) is not counted.  Those
held out give the thresholds: a document is rejected where its perplexity is above the QUANTILE of the held-out trusted
documents of its language.  Languages with fewer than LEAST_HELD take the quantile of all held-out ones; without any
nothing is rejected.  A null language is one of its own.  Rows that repeat, or share a doc_id, are scored each by its own text; an
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .base import cut, dealt_table, drop_dealt, fresh, partitions_of

ORDER, CHAR = 4, 15
START, END = 0, 1
#: Code points from WIDE up are pairs: one of LEADS, then one of 1024 symbols behind them.
WIDE, LEADS = 30_000, 30_002
BLOCK_CHARS = 12_000_000
FOLDS, QUANTILE = 5, 0.995
#: A language with fewer held-out texts takes the threshold of all languages: a quantile of few says little.
LEAST_HELD = 30
#: What a document is to the model: not trusted, trusted and counted, trusted and held out.
OTHER, COUNTED, HELD = 0, 1, 2
#: Up to so many trusted ids the flag is joined by broadcast (16 bytes each).
BROADCAST_IDS = 2_000_000
MAX_LANGS = 10_000


def symbols_of(text: str | None) -> np.ndarray:
    code = np.frombuffer((text or "").encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
    wide = code >= WIDE
    if not wide.any():
        return code + 2
    rest = code - WIDE
    pairs = np.where(wide, LEADS + (rest >> 10), code + 2), LEADS + (0x110000 >> 10) + (rest & 1023)
    return np.stack(pairs, 1).ravel()[np.stack([np.ones_like(wide), wide], 1).ravel()]


def gram_keys(texts: list[str | None], order: int = ORDER) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all positions of all texts, and the number of positions of each text."""
    raw = [symbols_of(t) for t in texts]
    sizes = np.array([len(r) + 1 for r in raw], np.int64)
    pad = np.full(order - 1, START, np.int64)
    parts: list[np.ndarray] = []
    for r in raw:
        parts += [pad, r, np.array([END])]
    flat = np.concatenate(parts) if parts else np.zeros(0, np.int64)
    key = np.zeros(max(0, len(flat) - order + 1), np.int64)
    for i in range(order):
        key = (key << CHAR) | flat[i : i + len(key)]
    # A window is a position of a text if it ends within it: the first order - 1 windows of all but the first straddle.
    ends = np.cumsum(sizes + order - 1)
    keep = np.ones(len(key), bool)
    for s in ends[:-1]:
        keep[s - order + 1 : s] = False
    return key[keep], sizes


def pack_blocks(docs: DataFrame, role: str, order: int = ORDER, block_chars: int = BLOCK_CHARS) -> DataFrame:
    """block, rows (Arrow stream), grams (compressed sorted keys and trusted counts)."""
    names = docs.columns
    at_text, at_flag = names.index("text"), names.index(role)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, seq, held, chars = TaskContext.get().partitionId(), 0, [], 0
        known, counts = np.zeros(0, np.int64), np.zeros(0, np.int64)

        def flush():
            block = pa.RecordBatch.from_arrays(
                [pa.array([task << 24 | seq], pa.int64()), pa.array([_to_stream(held)], pa.binary()), pa.array([_to_bytes(known, counts)], pa.binary())], names=["block", "rows", "grams"])
            return block

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                part = batch.slice(at, 64)
                texts = part.column(at_text).to_pylist()
                flags = part.column(at_flag).to_numpy() == COUNTED
                keys, sizes = gram_keys(texts, order)
                use = np.repeat(flags, sizes)
                k, inv = np.unique(keys, return_inverse=True)
                known, counts = _merged(known, counts, k, np.bincount(inv[use], minlength=len(k)))
                held.append(part)
                chars += len(keys)
                if chars >= block_chars:
                    yield flush()
                    seq, held, chars = seq + 1, [], 0
                    known, counts = np.zeros(0, np.int64), np.zeros(0, np.int64)
        if held:
            yield flush()

    return docs.mapInArrow(run, "block long, rows binary, grams binary")


def _merged(a: np.ndarray, ca: np.ndarray, b: np.ndarray, cb: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of two sorted key arrays, counts added."""
    if not len(a):
        return b, cb
    at = np.searchsorted(a, b)
    there = a[np.minimum(at, len(a) - 1)] == b
    ca = ca.copy()
    ca[at[there]] += cb[there]
    if there.all():
        return a, ca
    keys, vals = np.insert(a, at[~there], b[~there]), np.insert(ca, at[~there], cb[~there])
    return keys, vals


def _to_bytes(keys: np.ndarray, counts: np.ndarray) -> bytes:
    import zstandard

    steps = np.diff(keys, prepend=0)
    planes = np.concatenate([steps, counts.astype(np.int64)]).view(np.uint8).reshape(-1, 8).T  # bytes of one weight together
    return zstandard.ZstdCompressor(level=3).compress(np.ascontiguousarray(planes).tobytes())


def _from_bytes(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    import zstandard

    flat = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8)
    both = np.ascontiguousarray(flat.reshape(8, -1).T).view(np.int64).ravel()
    half = len(both) // 2
    return np.cumsum(both[:half]), both[half:]


def _to_stream(parts: list[pa.RecordBatch]) -> bytes:
    sink = pa.BufferOutputStream()
    whole = pa.Table.from_batches(parts).combine_chunks()
    with pa.ipc.new_stream(sink, whole.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 3))) as w:
        w.write_table(whole, max_chunksize=256)
    return sink.getvalue().to_pybytes()


def grams_of(packed: DataFrame) -> DataFrame:
    """block, key, c: the distinct n-grams of each block with their trusted counts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block, data in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                keys, counts = _from_bytes(data.as_py())
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), block)), pa.array(keys), pa.array(counts)], names=["block", "key", "c"])

    return packed.select("block", "grams").mapInArrow(run, "block long, key long, c long")


def count_tables(grams: DataFrame, order: int = ORDER) -> dict[int, DataFrame]:
    """(key, c) of each order: counts of the highest, numbers of distinct predecessors of the lower ones."""
    tables = {order: cut(grams.filter("c > 0").groupBy("key").agg(F.sum("c").alias("c")))}
    for k in range(order - 1, 0, -1):
        tables[k] = tables[k + 1].groupBy((F.col("key") % (1 << CHAR * k)).alias("key")).agg(F.count("*").alias("c"))
    return tables


def discounts(counts: DataFrame) -> list[float]:
    """The three discounts of one order, from its counts of counts."""
    n = counts.agg(*[F.count(F.when(F.col("c") == i, 1)).alias(f"n{i}") for i in range(1, 5)]).first()
    return discounts_from(*n)


def discounts_from(n1: int, n2: int, n3: int, n4: int) -> list[float]:
    y = n1 / (n1 + 2 * n2) if n1 else 0.5
    raw = [1 - 2 * y * n2 / n1 if n1 else 0.5, 2 - 3 * y * n3 / n2 if n2 else 1.0, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return [min(max(d, 0.1), i + 0.9) for i, d in enumerate(raw)]


def probabilities(asked: DataFrame, tables: dict[int, DataFrame], order: int = ORDER) -> DataFrame:
    """key, p of every distinct key in ``asked``: one order's count and context joins, then the next lower order's."""
    vocabulary = tables[1].count() + 1
    d = {k: discounts(tables[k]) for k in tables}

    def prob(keys: DataFrame, k: int) -> DataFrame:
        if k == 0:
            return keys.select("key", F.lit(1.0 / vocabulary).alias("p"))
        d1, d2, d3 = d[k]
        c = F.col("c")
        off = F.when(c == 1, d1).when(c == 2, d2).otherwise(d3)
        contexts = tables[k].groupBy(F.shiftright("key", CHAR).alias("h")).agg(F.sum("c").alias("total"), F.sum(off).alias("spare"))
        low = prob(keys.select((F.col("key") % (1 << CHAR * (k - 1))).alias("key")).distinct(), k - 1).select(F.col("key").alias("low_key"), F.col("p").alias("low"))
        # The context's rows first: its key is a prefix of the n-gram's.
        rows = keys.select("key", F.shiftright("key", CHAR).alias("hk"), (F.col("key") % (1 << CHAR * (k - 1))).alias("lk"))
        rows = rows.join(tables[k].select(F.col("key").alias("ck"), "c"), F.col("key") == F.col("ck"), "left")
        rows = rows.join(contexts, F.col("hk") == F.col("h"), "left").join(low, F.col("lk") == F.col("low_key"))
        seen = F.when(c.isNull(), 0.0).otherwise(c - off) / F.col("total")
        p = F.when(F.col("total").isNull(), F.col("low")).otherwise(seen + F.col("spare") / F.col("total") * F.col("low"))
        return rows.select("key", p.alias("p"))

    return prob(asked, order)


def answers_of(grams: DataFrame, p: DataFrame) -> DataFrame:
    """block, data: the log probabilities (base 2) of each block's n-grams, in the order of the block's keys.

    Rows come sorted, so a task holds the answers of one block.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []

        def done():
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int64()), pa.array([np.concatenate(held).tobytes()], pa.binary())], names=["block", "data"])

        for batch in batches:
            block, lp = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 2))
            cuts = np.flatnonzero(np.diff(block)) + 1
            for b, part in zip(block[np.r_[0, cuts]].tolist() if len(block) else [], np.split(lp, cuts), strict=False):
                if b != now and held:
                    yield done()
                    held = []
                now = b
                held.append(part)
        if held:
            yield done()

    joined = grams.select("block", "key").join(p.select(F.col("key").alias("pk"), F.log2("p").cast("float").alias("lp")), F.col("key") == F.col("pk"))
    return joined.select("block", "key", "lp").repartition(partitions_of(grams.sparkSession), "block").sortWithinPartitions("block", "key").mapInArrow(run, "block long, data binary")


def score_blocks(packed: DataFrame, answers: DataFrame, schema: str, order: int = ORDER) -> DataFrame:
    """All columns of the packed rows, then perplexity double.

    ``packed`` is bucketed by block and stays where it is; only the answers travel.
    """
    from .base import _arrow_schema

    out = _arrow_schema(packed.sparkSession, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, grams, data = batch.columns
            for i in range(batch.num_rows):
                keys, lps = _from_bytes(grams[i].as_py())[0], np.frombuffer(data[i].as_py(), np.float32)
                for part in pa.ipc.open_stream(rows[i].as_buffer()):
                    for at in range(0, part.num_rows, 64):
                        piece = part.slice(at, 64)
                        k, sizes = gram_keys(piece.column(piece.schema.names.index("text")).to_pylist(), order)
                        mean = np.add.reduceat(lps[np.searchsorted(keys, k)].astype(np.float64), np.cumsum(sizes) - sizes) / sizes
                        cols = [c.cast(f.type) for c, f in zip(piece.columns, out, strict=False)]
                        yield pa.RecordBatch.from_arrays([*cols, pa.array(np.exp2(-mean))], schema=out)

    got = answers.select(F.col("block").alias("b"), "data")
    return packed.join(got, F.col("block") == F.col("b")).select("rows", "grams", "data").mapInArrow(run, schema)


def with_role(docs: DataFrame, labels: DataFrame, out: str) -> DataFrame:
    """Add ``out``: what each row, by the label of its doc_id and the hash of its text, is to the model."""
    (ident,) = fresh(docs, "_id")
    ids = labels.filter((F.col("quality") == 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").alias(ident)).distinct()
    ids = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids
    held = F.pmod(F.xxhash64(docs["text"], F.lit("fold")), F.lit(FOLDS)) == 0
    role = F.when(F.col(ident).isNull(), OTHER).when(held, HELD).otherwise(COUNTED)
    return docs.join(ids, docs["doc_id"] == F.col(ident), "left").select(*[docs[f"`{c}`"] for c in docs.columns], role.alias(out))


def with_perplexity(docs: DataFrame, labels: DataFrame, role: str = "role", out: str = "perplexity", order: int = ORDER, block_chars: int = BLOCK_CHARS) -> tuple[DataFrame, DataFrame]:
    """``docs`` with two more columns, role and perplexity; and the table of packed blocks that it reads."""
    rows = with_role(docs, labels, role)
    packed = dealt_table(pack_blocks(rows, role, order, block_chars), "block", partitions_of(docs.sparkSession))
    grams = grams_of(packed)
    tables = count_tables(grams, order)
    asked = grams.select("key").distinct()
    answers = cut(answers_of(grams, probabilities(asked, tables, order)))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema) + f", `{out}` double"
    return score_blocks(packed, answers, schema, order), packed


def thresholds(scored: DataFrame, quantile: float = QUANTILE) -> tuple[DataFrame, float | None]:
    """lang, threshold of each language that has LEAST_HELD held-out trusted documents; the threshold of all of them."""
    level = F.percentile_approx("perplexity", quantile, 10_000)
    held = scored.filter(F.col("role") == HELD)
    by_lang = held.groupBy("lang").agg(level.alias("threshold"), F.count("*").alias("n")).filter(F.col("n") >= LEAST_HELD)
    return by_lang.select("lang", "threshold"), held.agg(level).first()[0]


def judged(scored: DataFrame, small: DataFrame, perplexity: str, threshold: str, keep: str, quantile: float = QUANTILE) -> DataFrame:
    """Add threshold and keep to scored rows.  ``small``: lang, role, perplexity of the same rows."""
    (lang,) = fresh([*scored.columns, threshold, keep], "_lang")
    by_lang, overall = thresholds(small, quantile)
    by_lang = cut(by_lang).select(F.col("lang").alias(lang), F.col("threshold").alias(threshold))
    by_lang = F.broadcast(by_lang) if by_lang.count() <= MAX_LANGS else by_lang
    level = F.coalesce(F.col(threshold), F.lit(overall).cast("double"))
    rows = scored.join(by_lang, scored["lang"].eqNullSafe(F.col(lang)), "left")
    return rows.select(*[scored[f"`{c}`"] for c in scored.columns], level.alias(threshold), F.coalesce(F.col(perplexity) <= level, F.lit(True)).alias(keep))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The registered query: doc_id, lang, trusted, held_out (trusted, but not counted), perplexity, threshold, keep."""
    scored, packed = with_perplexity(docs.select("doc_id", "lang", "text"), labels)
    scored = cut(scored.drop("text"))
    drop_dealt(docs.sparkSession, packed)
    out = judged(scored, scored, "perplexity", "threshold", "keep")
    return out.select("doc_id", "lang", (F.col("role") > OTHER).alias("trusted"), (F.col("role") == HELD).alias("held_out"), "perplexity", "threshold", "keep")


def keep_good(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are not rejected, all columns.

    The result reads a table in the checkpoint folder; ``base.drop_dealt`` removes it once the result is written.
    """
    own = docs.select(*[F.col(f"`{c}`").alias(c) for c in docs.columns])
    role, score, threshold, keep = fresh(docs, "role", "perplexity", "threshold", "keep")
    scored, _ = with_perplexity(own, labels, role, score)  # read once for the thresholds, once for the rows
    small = scored.select("lang", F.col(role).alias("role"), F.col(score).alias("perplexity"))
    return judged(scored, small, score, threshold, keep).filter(F.col(keep)).select(*[F.col(f"`{c}`") for c in docs.columns])
