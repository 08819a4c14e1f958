"""BPE encoding and decoding by a tokenization automaton.

The merges are compiled one after another.  A state of the automaton is "the last token emitted"; all arcs with one
label end in one state.  The gadget of a merge (a, b) -> c does three things: the state after ``a`` is copied and the
copy loses its arc ``b``; every state with an arc ``a`` gets an arc ``c``; ``c`` ends where ``b`` ended at that moment.

States are kept copy-on-write.  A state stores the state it was copied from, the time of the copy and the arcs it
lost.  Losing ``b`` at time t also loses every token that is later built from ``b`` as its left part; with the tokens
numbered in preorder of the "left part" forest, children by age, those tokens are one contiguous range.  So a
transition is a look-up in a few sorted ranges, and 49k merges compile in well under a second into a few MB.

The arcs of a state are laid out as one sorted row, the bounds of the ranges it lost, when a walk first enters the
state; all rows at once would be the square of the vocabulary.

Encoding reads a word once, symbol by symbol, and never goes back: every beginning of a word is spelled by exactly one
path, so one state belongs to each place.  A string automaton over the tokens tells which tokens end at a place, the
longest first; the state of the place is the one whose arc leaves the state at the place where it begins.  The path is
then read off from the end.  Decoding emits the labels of the arcs.

Null and empty texts have no ids; ids decode to their labels whatever their order.  Rows that repeat are rows like any
other; an empty table gives an empty result.  A vocabulary in which some word has no path (its merges are not all
reachable) falls back to merging that word pair by pair.
"""

from __future__ import annotations

import json
import unicodedata
from array import array
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import ArrayType, IntegerType, StructField, StructType

from .base import SLICE_ROWS, arrow_map

#: Words kept per worker with their ids; beyond it the memo is emptied.  It only saves time.
MEMO_WORDS = 200_000
#: Bounds of the rows of arcs kept per worker.
MEMO_BOUNDS = 6_000_000


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out = {b: chr(b) for b in plain}
    spare = iter(range(0x100, 0x200))
    return [out[b] if b in out else chr(next(spare)) for b in range(256)]


class Automaton:
    """Compiled merges.  ``allowed(a, b)``: may token b follow token a; ``encode(symbols)``: the token ids."""

    def __init__(self, vocab: dict[str, int], merges: list[tuple[str, str]]):
        self.vocab, n = vocab, max(vocab.values(), default=-1) + 1
        self.labels: list[str] = [""] * n
        for text, i in vocab.items():
            self.labels[i] = text
        left, right, age = [-1] * n, [-1] * n, [0] * n
        kids: list[list[int]] = [[] for _ in range(n)]
        gadgets = []
        for t, (a, b) in enumerate(merges, 1):
            c = vocab.get(a + b, -1)
            if c < 0 or a not in vocab or b not in vocab:
                continue
            ia, ib = vocab[a], vocab[b]
            if age[c]:
                # A second way to one token: the pair is still never left standing.
                gadgets.append((t, ia, ib))
                continue
            left[c], right[c], age[c] = ia, ib, t
            kids[ia].append(c)
            gadgets.append((t, ia, ib))
        self.right, self.age, self.kids = right, age, kids
        self.first, self.last = [0] * n, [0] * n  # preorder interval of each token's left-part subtree
        self._number(left)
        # Lost arcs of the state of a: (time, token, from, to); the children of b younger than the loss go with it.
        self.lost: list[list[tuple[int, int, int, int]]] = [[] for _ in range(n)]
        for t, a, b in gadgets:
            # Children are numbered by age, so those younger than t are the tail of b's interval.
            ages = [age[k] for k in kids[b]]
            j = bisect_left(ages, t)  # of age t: c itself where a = b
            start = self.first[kids[b][j]] if j < len(ages) else self.last[b]
            self.lost[a].append((t, self.first[b], start, self.last[b]))
        self._rows: dict[int, list[int]] = {}
        self._held = 0
        self._merges, self._rank = merges, None
        # A merge whose two parts no path has side by side makes nothing: its token, and those built from it, stay out.
        dead = [False] * n
        for t, a, b in gadgets:
            if dead[a] or dead[b] or not self._find(a, b, t):
                dead[vocab[self.labels[a] + self.labels[b]]] |= age[vocab[self.labels[a] + self.labels[b]]] == t
        vocab = {text: i for text, i in vocab.items() if not dead[i]}
        self.size = [0] * n
        self._compile(vocab)

    def _compile(self, vocab: dict[str, int]) -> None:
        """The string automaton: a trie of the tokens' symbols, and for each node the node of its longest proper suffix.

        ``ends[node]`` is the longest token that the node's string ends with, ``shorter[token]`` the next one.
        """
        self.step: list[dict[str, int]] = [{}]
        own = [-1]
        for text, i in vocab.items():
            node, symbols = 0, self._symbols(text)
            self.size[i] = len(symbols)
            for x in symbols:
                if (at := self.step[node].get(x)) is None:
                    at = self.step[node][x] = len(self.step)
                    self.step.append({})
                    own.append(-1)
                node = at
            own[node] = i
        self.fail, self.ends, self.shorter = [0] * len(own), own, [-1] * len(self.size)
        todo = list(self.step[0].values())
        for node in todo:  # level by level: the list grows as it is read
            for x, at in self.step[node].items():
                f = self.fail[node]
                while f and x not in self.step[f]:
                    f = self.fail[f]
                self.fail[at] = self.step[f].get(x, 0)
                below = self.ends[self.fail[at]]
                if self.ends[at] >= 0:
                    self.shorter[self.ends[at]] = below
                else:
                    self.ends[at] = below
                todo.append(at)

    def _number(self, left: list[int]) -> None:
        clock = 0
        for root in range(len(left)):
            if left[root] >= 0:
                continue
            todo = [(root, False)]
            while todo:
                node, done = todo.pop()
                if done:
                    self.last[node] = clock
                    continue
                self.first[node] = clock
                clock += 1
                todo.append((node, True))
                todo.extend((k, False) for k in reversed(self.kids[node]))

    @staticmethod
    def _symbols(text: str) -> list[str]:
        if text.endswith("</w>") and len(text) > 4:
            return [*text[:-5], text[-5:]]
        return list(text)

    def row(self, a: int) -> list[int]:
        """The arcs that the state after ``a`` lost, as bounds of ranges of numbers: begin, end, begin, end ..."""
        if (known := self._rows.get(a)) is not None:
            return known
        gone, x, until = [], a, 1 << 60
        while x >= 0:
            for t, own, lo, hi in self.lost[x]:
                if t < until:
                    gone.append((own, own + 1))
                    if lo < hi:
                        gone.append((lo, hi))
            until = min(until, self.age[x])  # the copy was made when x came to be
            x = self.right[x]
        out: list[int] = []
        for lo, hi in sorted(gone):
            if out and lo <= out[-1]:
                out[-1] = max(out[-1], hi)
            else:
                out += [lo, hi]
        if self._held + len(out) > MEMO_BOUNDS:
            self._rows.clear()
            self._held = 0
        self._held += len(out)
        self._rows[a] = out
        return out

    def allowed(self, a: int, b: int) -> bool:
        """Is there an arc b in the state after a?"""
        return bisect_right(self.row(a), self.first[b]) % 2 == 0

    def _find(self, a: int, b: int, until: int = 1 << 60) -> bool:
        x, at = a, self.first[b]
        while x >= 0:
            for t, own, lo, hi in self.lost[x]:
                if t < until and (at == own or lo <= at < hi):
                    return False
            until = min(until, self.age[x])  # the copy was made when x came to be
            x = self.right[x]
        return True

    def encode(self, symbols: list[str]) -> list[int]:
        """Ids of the one path that spells ``symbols``; symbols outside the vocabulary are left out first."""
        symbols = [s for s in symbols if s in self.vocab]
        step, fail, ends, shorter, size, first, rows = self.step, self.fail, self.ends, self.shorter, self.size, self.first, self._rows
        node, states = 0, [-1]
        for i, x in enumerate(symbols, 1):
            while (at := step[node].get(x)) is None and node:
                node = fail[node]
            node = at or 0
            token = ends[node]
            while token >= 0:
                last = states[i - size[token]]
                if i == size[token] or last >= 0 and bisect_right(rows[last] if last in rows else self.row(last), first[token]) % 2 == 0:
                    break
                token = shorter[token]
            states.append(token)
        path, i = [], len(symbols)
        while i:
            if (token := states[i]) < 0:
                return self.merged(symbols)
            path.append(token)
            i -= size[token]
        return path[::-1]

    def merged(self, symbols: list[str]) -> list[int]:
        """The same by merging, the oldest pair first, the leftmost of its kind first."""
        if (rank := self._rank) is None:
            v = self.vocab
            rank = self._rank = {(v[a], v[b]): (t, v[a + b]) for t, (a, b) in reversed(list(enumerate(self._merges, 1))) if a in v and b in v and a + b in v}
        ids = [self.vocab[s] for s in symbols]
        while pairs := [(rank[p], i) for i, p in enumerate(zip(ids, ids[1:], strict=False)) if p in rank]:
            (_, c), i = min(pairs)
            ids[i : i + 2] = [c]
        return ids


class Memo(dict):
    """A look-up that fills itself; beyond its size the older half of what it holds is given up."""

    def __init__(self, make, size: int):
        super().__init__()
        self.make, self.size, self.old = make, size, {}

    def __missing__(self, key):
        if (value := self.old.get(key)) is None:
            value = self.make(key)
        if len(self) >= self.size // 2:
            self.old = dict(self)
            self.clear()
        self[key] = value
        return value


class Tokenizer:
    """What a tokenizers-library BPE file with a word-end suffix describes: normalise, split, encode, decode."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.auto = Automaton(model["vocab"], [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in model["merges"]])
        self.added = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.suffix = model.get("end_of_word_suffix") or ""
        self.pieces = regex.compile(next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split"))
        self.labels = self.auto.labels + [""] * max(0, 1 + max(self.added.values(), default=-1) - len(self.auto.labels))
        for text, i in self.added.items():
            self.labels[i] = text
        self.special = regex.compile("|".join(map(regex.escape, sorted(self.added, key=len, reverse=True)))) if self.added else None
        self.bytes = byte_symbols()
        self.odd_space = regex.compile(r"[\x1c-\x1f]")
        self.space = regex.compile(r"[\t-\r \x85\xa0  -     　]+")
        self.memo, self.words = Memo(self._chunk, MEMO_WORDS), Memo(self._word, MEMO_WORDS)

    def _word(self, piece: str) -> bytes:
        """Packed ids of one pre-split word."""
        symbols = [self.bytes[b] for b in piece.encode("utf-8")]
        symbols[-1] += self.suffix
        return array("I", self.auto.encode(symbols)).tobytes()

    def _chunk(self, chunk: str) -> bytes:
        """Packed ids of a stretch without white space."""
        text = unicodedata.normalize("NFC", chunk).replace("Σ", "σ").lower()
        if len(text) > 64:  # not worth keeping
            return b"".join([self._word(p) if len(p) > 64 else self.words[p] for p in self.pieces.findall(text)])
        return b"".join(map(self.words.__getitem__, self.pieces.findall(text)))

    def packed(self, text: str) -> bytes:
        """Ids of a text as little-endian unsigned 32-bit integers."""
        if self.special is not None and "<" in text and (cuts := list(self.special.finditer(text))):
            out, at = [], 0
            for m in cuts:
                out += [self._plain(text[at : m.start()]), np.asarray([self.added[m[0]]], "<u4").tobytes()]
                at = m.end()
            return b"".join([*out, self._plain(text[at:])])
        return self._plain(text)

    def _plain(self, text: str) -> bytes:
        chunks = self.space.split(text) if self.odd_space.search(text) else text.split()
        if "" in chunks or max(map(len, chunks), default=0) > 64:
            return b"".join([self.memo[c] if len(c) <= 64 else self._chunk(c) for c in chunks if c])
        return b"".join(map(self.memo.__getitem__, chunks))

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.packed(text), "<u4").tolist()

    def decode(self, ids: list[int]) -> str:
        """Arc labels of the path, joined by a space (the file names no decoder)."""
        return " ".join(map(self.labels.__getitem__, ids))


def encode(df: DataFrame, tokenizer: str, text: str = "text", out: str = "ids") -> DataFrame:
    """Add ``out`` array<int>, the token ids of ``text``.  Null and empty texts have no ids; other columns stay.

    ``tokenizer`` is the path of the vocabulary file, readable on every executor.  A task holds the ids of SLICE_ROWS
    texts at a time.
    """
    schema = StructType([f for f in df.schema.fields if f.name != out] + [StructField(out, ArrayType(IntegerType()))])
    arrow = to_arrow_schema(schema)
    names = [f.name for f in schema.fields[:-1]]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = loaded(tokenizer)
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(at, SLICE_ROWS)
                packed = [tok.packed(t) if t else b"" for t in part.column(part.schema.get_field_index(text)).to_pylist()]
                ends = np.cumsum([0, *(len(x) // 4 for x in packed)], dtype=np.int32)
                ids = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.frombuffer(b"".join(packed), "<i4")))
                cols = [part.column(part.schema.get_field_index(n)).cast(f.type) for n, f in zip(names, arrow, strict=False)]
                yield pa.RecordBatch.from_arrays([*cols, ids.cast(arrow.field(out).type)], schema=arrow)

    return df.mapInArrow(run, schema)


def decode(df: DataFrame, tokenizer: str, ids: str = "ids", out: str = "decoded") -> DataFrame:
    """Add ``out``, the text of the labels of ``ids``.  Null is decoded as no ids."""
    return df.withColumn(out, F.pandas_udf(_decode_series(tokenizer), "string")(F.col(ids)))


def _decode_series(path: str):
    import pandas as pd

    def run(ids: pd.Series) -> pd.Series:
        tok = loaded(path)
        return pd.Series([tok.decode(list(x)) if x is not None else "" for x in ids])

    run.__annotations__ = {"ids": pd.Series, "return": pd.Series}
    return run


_LOADED: dict[str, Tokenizer] = {}


def loaded(path: str) -> Tokenizer:
    """One tokenizer per worker process."""
    if path not in _LOADED:
        _LOADED[path] = Tokenizer(path)
    return _LOADED[path]


def digests(docs: DataFrame, tokenizer: str) -> DataFrame:
    """Per document: doc_id, n_tokens, ids_sha256, decoded_sha256; encode, then decode the ids, in one pass."""
    from hashlib import sha256

    def make():
        tok = loaded(tokenizer)

        def kernel(cols):
            ids, texts = cols
            n, a, b = [], [], []
            for t in texts:
                packed = tok.packed(t or "")
                path = np.frombuffer(packed, "<u4").tolist()
                n.append(len(path))
                a.append(sha256(packed).hexdigest())
                b.append(sha256(tok.decode(path).encode("utf-8", "surrogatepass")).hexdigest())
            return [ids, n, a, b]

        return kernel

    return arrow_map(docs.select("doc_id", "text"), make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
