"""Toxicity by compression distance.

Two zstandard dictionaries are trained on labelled texts, one on windows of toxic texts and one on windows of ordinary
ones.  A window is a word between spaces.  Every window of a text is compressed with either dictionary, before a fixed frame
that both dictionaries end with (alone, so few bytes would be stored as they are); the difference of the two lengths
says in which of the two it is the more at home.  A text's score is a logistic function,
fitted on labelled texts, of how many windows lie beyond each of a few differences.

The toxic dictionary is trained on the windows whose share of toxic texts is so many times their share of ordinary ones
or more: both kinds share most of their words, and a dictionary has room for little.  It may hold beginnings of windows
as well, so that words that were never seen, but are formed like those of toxic texts, are the shorter for it.  What
share and whether beginnings is chosen among CHOICES by the likelihood of training texts that neither dictionary nor
weights have seen.

Training reads at most TRAIN_DOCS texts of either class, the first by md5 of doc_id, of a doc_id one text (that of the
smallest hash), and of those the first TRAIN_BYTES bytes' worth of whole texts; scoring reads every whole text.
Null and empty texts have no window and get the score of an empty text.  Without labels of both classes every score is
the share of toxic labels (0.0 without any).  Rows that repeat are scored each by its text; labels that contradict each
other count as toxic; an empty table gives an empty result.
"""

from __future__ import annotations

from collections import Counter
from zlib import crc32

import numpy as np
import zstandard as zstd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import arrow_map

#: Bounds of the fitting sample: texts of a class, and bytes of their texts.
TRAIN_DOCS, TRAIN_BYTES = 3000, 32_000_000
#: How many times the share must be, and whether beginnings count.
CHOICES = ((4.0, False), (8.0, False), (4.0, True))
#: Standard errors by which the two shares must differ as well.
SURE = 3.0
DICT_BYTES = 1 << 15
#: Differences of compressed lengths, in bytes, whose exceedances are counted.
STEPS = (1, 2, 3, 4, 5, 7)
FRAME = bytes(range(128, 176))
#: Code points of the shortest beginning of a window that counts by itself.
STEM = 4
LONGEST = 48  # code points of a word that one window holds; a longer word is cut into several windows
MEMO_WORDS = 400_000


def windows(text: str) -> list[str]:
    out = []
    for w in text.lower().split():
        if len(w) <= LONGEST:
            out.append(w)
        else:
            out += [w[i : i + LONGEST] for i in range(0, len(w), LONGEST)]
    return out


def pieces(text: str) -> set[str]:
    """The windows of a text between spaces, and their beginnings of STEM code points or more behind one."""
    out = set()
    for w in set(windows(text)):
        out.add(f" {w} ")
        out.update(f" {w[:k]}" for k in range(STEM, len(w)))
    return out


def samples(words: list[str], df: Counter, length: int = 300, most: int = 60) -> list[bytes]:
    """Samples for the trainer, which passes over very short ones: pieces side by side, each as often as in texts."""
    again = [(crc32(f"{i} {w}".encode("utf-8", "surrogatepass")), w) for w in words for i in range(min(df[w], most))]
    out, now = [], ""
    for _, w in sorted(again):
        now += w
        if len(now) >= length:
            out.append(now.encode("utf-8", "surrogatepass"))
            now = ""
    return [*out, now.encode("utf-8", "surrogatepass")]


def train_dictionary(samples: list[bytes], size: int = DICT_BYTES) -> bytes:
    """zstandard's trainer; where it has too little to go by, the samples themselves, most frequent last."""
    try:
        return zstd.train_dictionary(size, samples, k=32, d=6, notifications=0).as_bytes()
    except (zstd.ZstdError, ValueError, MemoryError):
        ranked = [s for s, _ in Counter(samples).most_common()]
        kept, left = [], size
        for s in ranked:
            if (left := left - len(s)) < 0:
                break
            kept.append(s)
        return b"".join(reversed(kept))


class Distance:
    """Difference of a window's compressed lengths: ordinary less toxic."""

    def __init__(self, toxic: bytes, ordinary: bytes):
        params = zstd.ZstdCompressionParameters.from_level(6, write_content_size=0, write_checksum=0, write_dict_id=0)
        self.sides = []
        for d in (ordinary, toxic):
            kind = zstd.DICT_TYPE_AUTO if d[:4] == b"\x37\xa4\x30\xec" else zstd.DICT_TYPE_RAWCONTENT
            held = zstd.ZstdCompressionDict(d + FRAME, dict_type=kind)
            held.precompute_compress(compression_params=params)
            self.sides.append(zstd.ZstdCompressor(dict_data=held, compression_params=params))
        self.memo: dict[str, int] = {}

    def of(self, window: str) -> int:
        if (known := self.memo.get(window)) is None:
            data = f" {window} ".encode("utf-8", "surrogatepass") + FRAME
            a, b = (len(c.compress(data)) for c in self.sides)
            if len(self.memo) >= MEMO_WORDS:
                self.memo.clear()
            known = self.memo[window] = a - b
        return known

    def features(self, text: str | None) -> np.ndarray:
        memo, ws = self.memo, windows(text or "")
        d = np.fromiter((memo[w] if w in memo else self.of(w) for w in ws), np.int64, len(ws))
        over = [(d >= s).sum() for s in STEPS]
        n = max(1, len(d))
        return np.array([*np.log1p(over), *(np.minimum(1.0, 20.0 * o / n) for o in over), max(0, d.max(initial=0)) / 8.0])


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 50) -> np.ndarray:
    """Newton steps on the penalised likelihood; the intercept is the last weight and is not penalised."""
    a = np.hstack([x, np.ones((len(x), 1))])
    w = np.zeros(a.shape[1])
    pen = np.full(a.shape[1], ridge)
    pen[-1] = 1e-9
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + np.diag(pen), a.T @ (y - p) - pen * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


class Model:
    def __init__(self, toxic: bytes, ordinary: bytes, weights: np.ndarray):
        self.toxic, self.ordinary, self.weights = toxic, ordinary, weights

    def scorer(self):
        dist, w = Distance(self.toxic, self.ordinary), self.weights
        if len(w) == 1:
            return lambda text: float(w[0])
        return lambda text: float(1 / (1 + np.exp(-np.clip(dist.features(text) @ w[:-1] + w[-1], -30, 30))))


def dictionaries(df: dict[int, Counter], n: Counter, contrast: float, beginnings: bool) -> tuple[bytes, bytes]:
    """The toxic and the ordinary dictionary, from the numbers of texts of a class that hold a piece."""
    share = lambda w, c: (df[c][w] + 0.5) / (n[c] + 1)
    gap = lambda w: (share(w, 1) - share(w, 0)) / np.sqrt(share(w, 1) / (n[1] + 1) + share(w, 0) / (n[0] + 1))
    marked = [w for w, k in df[1].items() if k >= 2 and (beginnings or w[-1] == " ") and share(w, 1) >= contrast * share(w, 0) and gap(w) >= SURE]
    plain = [w for w, k in df[0].most_common(60_000) if k >= 2 and w[-1] == " "] or list(df[0])
    return train_dictionary(samples(marked or list(df[1]), df[1])), train_dictionary(samples(plain, df[0]), 4 * DICT_BYTES)


def train(texts: list[str | None], labels: list[int], toxic_share: float | None = None) -> Model:
    """Dictionaries from one half of the texts, weights from the other half: lengths of windows that a dictionary was
    trained on would look better than those of new ones.  One of CHOICES is taken with weights from one part of the other
    half and the likelihood of the rest.  ``toxic_share``: among all labelled texts, where the sample is balanced
    otherwise; the intercept is moved to it."""
    y = np.array(labels, float)
    if len(set(labels)) < 2:
        return Model(b"", b"", np.array([y.mean() if len(y) else 0.0]))
    df = {0: Counter(), 1: Counter()}
    n = Counter()
    halves = [i % 2 == 0 for i in range(len(texts))] if len(texts) >= 40 else [True] * len(texts)
    for t, label, use in zip(texts, labels, halves, strict=True):
        if use:
            df[label].update(pieces(t or ""))
            n[label] += 1
    rows = [i for i, use in enumerate(halves) if not use] or list(range(len(texts)))
    if len({labels[i] for i in rows}) < 2:
        rows = list(range(len(texts)))
    first, rest = np.arange(len(rows)) % 3 > 0, np.arange(len(rows)) % 3 == 0
    best = None
    for choice in CHOICES:
        pair = dictionaries(df, n, *choice)
        dist = Distance(*pair)
        x = np.array([dist.features(texts[i]) for i in rows])
        w = fit_logistic(x[first], y[rows][first])
        z = np.clip(x[rest] @ w[:-1] + w[-1], -30, 30)
        loss = float(np.logaddexp(0, z).sum() - (z * y[rows][rest]).sum())
        if best is None or loss < best[0]:
            best = (loss, pair, x)
    _, (toxic, ordinary), x = best
    weights = fit_logistic(x, y[rows])
    if toxic_share is not None and 0 < toxic_share < 1:
        here = y[rows].mean()
        weights[-1] += np.log(toxic_share / (1 - toxic_share)) - np.log(here / (1 - here))
    return Model(toxic, ordinary, weights)


def held_out(doc_id="doc_id"):
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5 == 0


def training_rows(docs: DataFrame, labels: DataFrame, per_class: int = TRAIN_DOCS, most: int = TRAIN_BYTES) -> DataFrame:
    """doc_id, text, toxic: at most ``per_class`` labelled texts and ``most`` bytes of a class, none held out."""
    from pyspark.sql import Window as W

    known = labels.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out()).select(F.col("doc_id").alias("i"), F.col("toxic").cast("int").alias("toxic")).groupBy("i").agg(F.max("toxic").alias("toxic"))
    key = F.md5(F.col("i").cast("string").cast("binary"))
    picked = [known.filter(F.col("toxic") == c).orderBy(key, "i").limit(per_class) for c in (0, 1)]
    few = picked[0].unionByName(picked[1])  # at most 2 x per_class rows
    texts = docs.select("doc_id", "text").join(F.broadcast(few), F.col("doc_id") == F.col("i"))
    one = texts.groupBy("i").agg(F.min("toxic").alias("toxic"), F.min_by("text", F.xxhash64("text")).alias("text"))
    w = W.partitionBy("toxic").orderBy(key, "i")  # over at most per_class rows
    return one.withColumn("bytes", F.sum(F.coalesce(F.octet_length("text"), F.lit(0)).cast("long")).over(w)).filter(F.col("bytes") <= most).select(F.col("i").alias("doc_id"), "text", "toxic")


def fit(docs: DataFrame, labels: DataFrame, per_class: int = TRAIN_DOCS) -> Model:
    rows = sorted(training_rows(docs, labels, per_class).collect(), key=lambda r: (r["doc_id"], r["text"] or ""))
    n = {r["toxic"]: r["n"] for r in labels.filter(F.col("toxic").isin(0, 1) & ~held_out()).groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    return train([r["text"] for r in rows], [r["toxic"] for r in rows], n.get(1, 0) / max(1, sum(n.values())))


def scores(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score of every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # two dictionaries of a fixed size

    def make():
        score = shared.value.scorer()

        def kernel(cols):
            ids, texts = cols
            return [ids, [score(t) for t in texts]]

        return kernel

    return arrow_map(docs.select("doc_id", "text"), make, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The digest of the registered query."""
    return scores(docs, fit(docs, labels)).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
