"""Secret scans: base patterns, and multipart credentials linked by an interval join inside one scope.

A credential often comes in parts: an access identifier, a secret and an endpoint, none of which proves much alone.
The parts of a text are intervals of code points.  A scope is a paragraph (blank lines end it).  Two parts are joined
if they lie in one scope and the gap between them is at most ``reach`` code points; the registered query and the
redaction set no reach, so that any two parts of a scope are joined, however far apart.  The cost of the join follows the number of parts, not its square: for a
candidate only the nearest part of each complementary kind is looked up.

Weak candidates (a long mixed token without a keyword, a bare user or client identifier, an endpoint with no user
part) are reported only where complementary parts occur: a secret needs an access identifier or an endpoint in reach,
an identifier needs a secret.

Results: null and empty texts have no spans; equal spans of one kind are reported once.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from hashlib import sha256
from itertools import accumulate

from pyspark.sql import DataFrame

from .base import arrow_map

#: Fixed values of the base patterns.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")  # the same as maximal runs of [0-9a-f], the short ones dropped
ASSIGN_LEAST, ACCESS_LEAST = 6, 20
KINDS = ("assign", "access", "hex", "weak_id", "weak_secret", "weak_endpoint")

#: Patterns of the parts that are weak alone.
WEAK_ID = re.compile(r"""\b(?:access_?key(?:_?id)?|client_?id|account|username|user|login)["']?\x20*[:=]\x20*["']?([A-Za-z0-9._@-]{3,})""", re.I | re.A)
WEAK_SECRET = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{20,}+={0,2}(?![A-Za-z0-9+/_=-])")
WEAK_ENDPOINT = re.compile(r"""\b(?:https?|ftp|s3|jdbc:[a-z]+|amqp|redis|postgres(?:ql)?|mysql|mongodb(?:\+srv)?)://[^\s"'<>|]{3,}|\b(?:endpoint|host|server|region)["']?\x20*[:=]\x20*["']?[A-Za-z0-9.:-]{3,}""", re.I | re.A)
BLANK = re.compile(r"\n[ \t]*\n")
#: One of these must occur before the costlier patterns of weak parts are tried; each weak pattern needs one.
HINT = re.compile(r"://|[:=]", re.A)


def entropy(s: str) -> float:
    """Bits per character."""
    n = len(s)
    return -sum(k / n * math.log2(k / n) for k in map(s.count, set(s))) if n else 0.0


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the base patterns, by start, then kind as listed."""
    out = [(m.start(), m.end(), 0) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= ASSIGN_LEAST]
    if "AKIA" in text:
        out += [(m.start(), m.end(), 1) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_LEAST]
    out += [(m.start(), m.end(), 2) for m in HEX.finditer(text)]
    out.sort(key=lambda s: (s[0], s[2]))
    return [(a, b, KINDS[k]) for a, b, k in out]


def linked_spans(text: str, base: list[tuple[int, int, str]], reach: int | None = 200) -> list[tuple[int, int, str]]:
    """Weak candidates that a complementary part of their scope supports, in reach if there is one."""
    reach = math.inf if reach is None else reach
    ids = [(m.start(1), m.end(1)) for m in WEAK_ID.finditer(text)]
    ends = [(m.start(), m.end()) for m in WEAK_ENDPOINT.finditer(text)]
    strong_ids = [(a, b) for a, b, k in base if k == "access"]
    strong_secrets = [(a, b) for a, b, k in base if k in ("assign", "hex")]
    if not (ids or ends or strong_ids):
        return []
    taken = sorted([*strong_ids, *strong_secrets, *ids, *ends])
    starts = [a for a, _ in taken]
    furthest = list(accumulate((b for _, b in taken), max))

    def covered(a: int, b: int) -> bool:
        i = bisect_left(starts, b)
        return i > 0 and furthest[i - 1] > a

    secrets = []
    for m in WEAK_SECRET.finditer(text):
        s = m[0]
        mixed = any(c.isdigit() for c in s) and any(c.isupper() for c in s) and any(c.islower() for c in s)
        if mixed and entropy(s) >= 3.5 and not covered(m.start(), m.end()):
            secrets.append((m.start(), m.end()))
    scopes = [m.end() for m in BLANK.finditer(text)]

    def near(parts: list[tuple[int, int]]):
        parts = sorted(parts)
        at = [a for a, _ in parts]
        # The furthest end among the parts up to each one: an early long part can reach past later ones.
        best, top = [], (-1, -1)
        for a, b in parts:
            top = max(top, (b, a))
            best.append(top)

        def find(a: int, b: int) -> bool:
            scope = bisect_left(scopes, a + 1)
            i = bisect_left(at, a)
            if i < len(at) and at[i] - b <= reach and bisect_left(scopes, at[i] + 1) == scope:
                return True
            return i > 0 and a - best[i - 1][0] <= reach and bisect_left(scopes, best[i - 1][0]) == scope

        return find

    all_secrets = [*strong_secrets, *secrets]
    id_near, end_near, secret_near = near([*ids, *strong_ids]), near(ends), near(all_secrets)
    out = [(a, b, "weak_secret") for a, b in secrets if id_near(a, b) or end_near(a, b)]
    out += [(a, b, "weak_id") for a, b in ids if secret_near(a, b)]
    out += [(a, b, "weak_endpoint") for a, b in ends if secret_near(a, b) and id_near(a, b)]
    return sorted(set(out), key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def scan(text: str | None, reach: int | None = 200) -> tuple[list[tuple[int, int, str]], list[tuple[int, int, str]]]:
    """(base spans, all spans) of one text."""
    text = text or ""
    base = base_spans(text)
    more = linked_spans(text, base, reach) if HINT.search(text) or base else []
    return base, sorted([*base, *more], key=lambda s: (s[0], KINDS.index(s[2]), s[1]))


def joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def redact(text: str | None, reach: int | None = 200, mark: str = "[SECRET]") -> str | None:
    """The text with every reported span replaced; overlapping spans become one mark."""
    if not text:
        return text
    out, at = [], 0
    for a, b, _ in scan(text, reach)[1]:
        if a >= at:
            out += [text[at:a], mark]
        at = max(at, b)
    return "".join([*out, text[at:]]) if at else text


def find_secrets(docs: DataFrame, reach: int | None = None) -> DataFrame:
    """One row per document: doc_id, counts of base spans, their digest, and all spans."""

    def make():
        def kernel(cols):
            ids, texts = cols
            out = [ids, [], [], [], [], []]
            for t in texts:
                base, spans = scan(t, reach)
                kinds = [k for _, _, k in base]
                for c, v in zip(out[1:], (kinds.count("assign"), kinds.count("access"), kinds.count("hex"), sha256(joined(base).encode()).hexdigest(), joined(spans)), strict=True):
                    c.append(v)
            return out

        return kernel

    return arrow_map(docs.select("doc_id", "text"), make, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redacted(docs: DataFrame, reach: int | None = None, text: str = "text") -> DataFrame:
    """``docs`` with the secrets of ``text`` replaced; all columns stay, in order."""
    import pandas as pd
    from pyspark.sql import functions as F

    def run(texts: pd.Series) -> pd.Series:
        return texts.map(lambda t: redact(t, reach))

    run.__annotations__ = {"texts": pd.Series, "return": pd.Series}
    return docs.withColumn(text, F.pandas_udf(run, "string")(F.col(text)))
