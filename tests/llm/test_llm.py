"""Text operators against brute force, and their answers to nulls, empty and long texts, ties, repeats, empty tables and
columns whose names clash."""

import hashlib
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from relprop.llm import base, bpe, components, decontaminate, htmltext, jaccard, licenses, merkle, quality, queries, secrets, simhash, suffix_dedup, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, key string, block string, fp string"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in any column, empty and very long texts, repeated rows, extra columns with the operators' own names."""
    long = " ".join(f"word{i % 977} and more." for i in range(20_000))
    rows = [(1, "", "en"), (2, None, "en"), (3, "one", None), (4, "a b c d e f g h i j k", "de"), (4, "a b c d e f g h i j k", "de"), (None, "no id here at all", "en"), (None, None, None), (7, long, "en"), (8, long + " end", "en"), (9, "password: hunter2hunter2 \U0001f600 é漢字́", "fr")]
    return spark.createDataFrame([(i, t, lang, "s", len(t or ""), "k", "b", "f") for i, t, lang in rows], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] for r in docs.collect()}


@pytest.fixture(scope="module")
def labels(spark, sf):
    return spark.read.parquet(f"{sf}/labels.parquet")


def empty(df):
    return df.filter("false")


def low(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def no_labels(spark):
    return spark.createDataFrame([], "doc_id long, quality int, toxic int")


# 1

def kneser_ney(trusted, asked, order=4):
    """Textbook recursion over dictionaries."""
    symbols = lambda o: [o + 2] if o < 30_000 else [30_002 + (o - 30_000) // 1024, 31_090 + (o - 30_000) % 1024]
    pad = lambda t: [0] * (order - 1) + [x for c in t for x in symbols(ord(c))] + [1]
    counts = {order: Counter(tuple(s[i : i + order]) for s in map(pad, trusted) for i in range(len(s) - order + 1))}
    for k in range(order - 1, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    d = {k: quality.discounts_from(*[sum(c == i for c in counts[k].values()) for i in range(1, 5)]) for k in counts}
    ctx = {k: defaultdict(list) for k in counts}
    for k in counts:
        for g, c in counts[k].items():
            ctx[k][g[:-1]].append(c)
    off = lambda k, c: d[k][min(c, 3) - 1]

    def p(g, k):
        if k == 0:
            return 1 / (len(counts[1]) + 1)
        below = p(g[1:], k - 1)
        have = ctx[k].get(g[:-1])
        if not have:
            return below
        c, total = counts[k].get(g, 0), sum(have)
        return ((c - off(k, c)) if c else 0) / total + sum(off(k, x) for x in have) / total * below

    out = []
    for t in asked:
        s = pad(t or "")
        lp = [np.log2(p(tuple(s[i : i + order]), order)) for i in range(len(s) - order + 1)]
        out.append(2 ** -np.mean(lp))
    return out


def test_perplexity_is_the_textbooks(spark):
    rows = [(i, t, "en") for i, t in enumerate(["the cat sat", "the dog sat on the mat", "a cat and a dog", "zzz qqq", "", None, "the the the cat", "\U0001f600 odd 각꿔 \ud7a3", "\U0001f600 even 각"])]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    lab = spark.createDataFrame([(0, 1), (1, 1), (2, 1), (3, 0), (8, 1)], "doc_id long, quality int")
    got = {r["doc_id"]: r for r in quality.with_perplexity(df, lab, block_chars=20)[0].collect()}
    counted = [t for i, t, _ in rows if got[i]["role"] == quality.COUNTED]
    assert {i for i in got if got[i]["role"] != quality.OTHER} == {0, 1, 2, 8} and len(counted) >= 2
    want = kneser_ney(counted, [t for _, t, _ in rows])
    assert all(abs(got[i]["perplexity"] / w - 1) < 1e-5 for i, w in enumerate(want)), (got, want)


def test_code_points_are_told_apart():
    every = [chr(o) for o in [*range(29_000, 31_000), *range(0xAC00, 0xD7A4, 7), 0x10000, 0x1F600, 0x10FFFF]]
    seen = {tuple(quality.symbols_of(c)) for c in every}
    assert len(seen) == len(every) and max(max(x) for x in seen) < 1 << quality.CHAR
    assert quality.symbols_of("a각b").tolist() == [99, 30_002 + 14_033 // 1024, 31_090 + 14_033 % 1024, 100]


def test_quality_tells_junk_from_prose(spark, docs, labels):
    got = quality.classify(docs, labels).join(labels, "doc_id").groupBy("quality").agg(F.avg(F.col("keep").cast("int")).alias("k")).collect()
    kept = {r["quality"]: r["k"] for r in got}
    assert kept[1] > 0.97 and kept[0] < 0.5


def test_thresholds_are_quantiles_of_held_out_texts(spark, monkeypatch):
    """Threshold and keep against plain Python, with languages that have few or no held-out texts and a null one."""
    monkeypatch.setattr(quality, "LEAST_HELD", 8)
    rng = np.random.default_rng(4)
    text = lambda: "".join(rng.choice(list("abcd efg"), int(rng.integers(5, 60))))
    rows = [(i, text(), ("en", "en", "de", None, "xx")[i % 5]) for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    lab = spark.createDataFrame([(i, 1) for i in range(150) if i % 5 != 4], "doc_id long, quality int")
    got = quality.classify(df, lab).collect()
    held = defaultdict(list)
    for r in got:
        if r["held_out"]:
            held[r["lang"]].append(r["perplexity"])
            held[...].append(r["perplexity"])
    assert set(held) == {"en", "de", None, ...} and all(r["trusted"] for r in got if r["held_out"])
    assert len({len(x) >= 8 for x in held.values()}) == 2
    for r in got:
        p = sorted(held[r["lang"]] if len(held.get(r["lang"], [])) >= 8 else held[...])
        assert r["threshold"] == p[int(np.ceil(quality.QUANTILE * len(p))) - 1] and r["keep"] == (r["perplexity"] <= r["threshold"])
    kept = {r["doc_id"] for r in quality.keep_good(df, lab).collect()}
    assert kept == {r["doc_id"] for r in got if r["keep"]}


def test_quality_of_odd_rows(spark, odd, labels):
    assert quality.classify(odd, no_labels(spark)).filter("keep").count() == odd.count()
    kept = quality.keep_good(odd, labels)
    assert kept.columns == odd.columns and kept.count() <= odd.count()
    assert quality.classify(empty(odd), labels).count() == 0 and quality.keep_good(empty(odd), labels).count() == 0
    base.drop_dealt(spark)
    assert not [t.name for t in spark.catalog.listTables() if t.name.startswith("dealt_")]


# Columns that are called as the operators call theirs

HOSTILE = "_id _th _many _turn _hit_id _hit_key _spans _lang _threshold _tree _key _n role perplexity threshold keep trusted spans ids key fp row_key b inner head".split()


@pytest.fixture(scope="module")
def hostile(spark):
    """Such columns, ids at the ends of the range, different texts of one id, copies without an id."""
    rows = [(-(2**62) - 5, "first text about apples and pears and plums today"), (2**62 + 7, "B c D e f g h i j k"), (1, "first text of its own kind in here"), (1, "another one with nothing like it at all"), (None, "first text of its own kind in here"), (None, None), (3, ""), (2**63 - 1, "x"), (-(2**63), "y")]
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), *["clash"] * len(HOSTILE)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"`{c}` string" for c in HOSTILE))


def test_hostile_columns_ids_and_repeats(spark, hostile, labels):
    bench = spark.createDataFrame([(5, "b c d e f g h i j k")], "item_id long, text string")
    n = hostile.count()
    kept = simhash.deduplicate(hostile)
    assert kept.columns == hostile.columns
    left = [(r["doc_id"], r["text"]) for r in kept.collect()]
    assert (1, "another one with nothing like it at all") in left and (1, "first text of its own kind in here") in left
    assert (None, "first text of its own kind in here") not in left and (3, "") in left and (None, None) not in left
    near = jaccard.deduplicate(hostile)
    assert near.columns == hostile.columns and sorted(map(str, left)) == sorted(str((r["doc_id"], r["text"])) for r in near.collect())
    for out, rows in ((decontaminate.remove(hostile, bench), n - 1), (decontaminate.remove(hostile, bench, mode="spans"), n), (suffix_dedup.remove(hostile), n), (secrets.redacted(hostile), n), (quality.keep_good(hostile, labels), n), (quality.keep_good(hostile, no_labels(spark)), n)):
        assert out.columns == hostile.columns and out.count() == rows and {r["keep"] for r in out.collect()} == {"clash"}
    prints = merkle.with_fingerprint(hostile)
    assert prints.columns == [*hostile.columns, "fingerprint"] and {r["_tree"] for r in prints.collect()} == {"clash"}
    got = {(r["doc_id"], r["n_chars"]): r for r in merkle.fingerprints(hostile).collect()}
    assert len(got) == n
    first = next(r["text"] for r in hostile.collect() if r["doc_id"] == 2**62 + 7)
    assert got[2**63 - 1, 1]["edited_sha256"] == hashlib.sha256(b"x").hexdigest()
    edited = first[: len(first) - len(first) // 2] + ""  # the next document is the empty one
    assert got[2**62 + 7, len(first)]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
    for call in (suffix_dedup.summary, simhash.summary, secrets.find_secrets):
        assert call(hostile).count() == n


def test_a_repeated_row_is_one_row(spark):
    rows = [(4, "the same text again", "a")] * 3 + [(4, "the same text again", "b"), (None, "alone", "c"), (None, "alone", "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, other string")
    for f in (simhash.deduplicate, jaccard.deduplicate):
        assert sorted((r["doc_id"], r["text"]) for r in f(df).collect() if r["doc_id"]) == [(4, "the same text again")] and f(df).count() == 2


# 2

def brute_contamination(texts, items):
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    grams = defaultdict(set)
    for i, t in items.items():
        w = word.findall(low(t))
        for g in ([tuple(w[k : k + 10]) for k in range(len(w) - 9)] or [tuple(w)]) if w else []:
            grams[g].add(i)
    sizes = {len(g) for g in grams}
    out = {}
    for d, t in texts.items():
        w, hit, found = word.findall(low(t)), set(), set()
        for n in sizes:
            for k in range(len(w) - n + 1):
                if (g := tuple(w[k : k + n])) in grams:
                    hit.update(range(k, k + n))
                    found |= grams[g]
        out[d] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(map(str, found))).encode()).hexdigest(), bool(hit))
    return out


def test_contamination_is_brute_forces(spark, docs, texts, sf):
    bench = spark.read.parquet(f"{sf}/benchmark.parquet")
    extra = spark.createDataFrame([(900, "The OF"), (901, ""), (902, None), (903, "!!")], "item_id long, text string")
    bench = bench.unionByName(extra)
    got = {r[0]: tuple(r)[1:] for r in decontaminate.summary(docs, bench).collect()}
    assert got == brute_contamination(texts, {r["item_id"]: r["text"] for r in bench.collect()})


def test_contamination_without_broadcast_and_removal(spark, odd, monkeypatch):
    bench = spark.createDataFrame([(5, "B c D e f g h i j k")], "item_id long, text string")
    want = decontaminate.summary(odd, bench).orderBy("doc_id", "n_words").collect()
    monkeypatch.setattr(decontaminate, "BROADCAST_WINDOWS", 0)
    assert decontaminate.summary(odd, bench).orderBy("doc_id", "n_words").collect() == want and len(want) == odd.count()
    assert decontaminate.remove(odd, bench).count() == odd.count() - 2
    spans = decontaminate.remove(odd, bench, mode="spans")
    assert spans.columns == odd.columns and {r["text"] for r in spans.filter("doc_id = 4").collect()} == {"a "}
    assert decontaminate.summary(odd, empty(bench)).filter("n_hit > 0").count() == 0
    assert decontaminate.summary(empty(odd), bench).count() == 0


def test_native_operators_run_no_python(spark, docs, sf):
    for df in (decontaminate.summary(docs, spark.read.parquet(f"{sf}/benchmark.parquet")), merkle.fingerprints(docs)):
        assert not re.search("Python|Pandas|Arrow", df._jdf.queryExecution().executedPlan().toString())


# 3

def test_licenses_found_and_placed(spark, docs, texts, odd):
    got = {(r["doc_id"], r["license"]): r for r in licenses.scan_licenses(docs).filter("matched").collect()}
    marks = {"MIT": "Released under the MIT License", "Apache-2.0": "Licensed under the Apache License, Version 2.0", "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0"}
    for name, text in marks.items():
        have = {d for d, t in texts.items() if text in (t or "")}
        assert {d for d, n in got if n == name} == have
        assert all(texts[d][got[d, name]["start"] : got[d, name]["end"]] == text for d in have)
    assert licenses.scan_licenses(odd).count() == 0 and licenses.scan_licenses(empty(odd)).count() == 0


def test_repeated_notices_are_all_found():
    scanner, line = licenses.Scanner(licenses.TEMPLATES), "Released under the MIT License."
    for n in (2, 3, 7, 40):
        text = "\n".join([line] * n)
        assert [(a, b) for _, _, a, b in scanner.scan(text)] == [(i * (len(line) + 1), i * (len(line) + 1) + len(line) - 1) for i in range(n)]
    mixed = [line, "Licensed under CC BY 4.0.", line, "Released under the well MIT License.", "Licensed under CC BY 4.0."]
    assert [m[0] for m in scanner.scan(" ".join(mixed))] == ["MIT", "CC-BY-4.0", "MIT", "MIT", "CC-BY-4.0"]


def plain_alignment(text, template):
    """Best matched words of a template against a whole text: match 1, others -1, free ends in the text."""
    rows = [[(0, 0)] * (len(text) + 1)]
    for w in template:
        row = [(rows[-1][0][0] - 1, rows[-1][0][1])]
        for j, t in enumerate(text):
            s, m = rows[-1][j]
            row.append(max((s + (1 if t == w else -1), m + (t == w)), (rows[-1][j + 1][0] - 1, rows[-1][j + 1][1]), (row[-1][0] - 1, row[-1][1])))
        rows.append(row)
    return max(rows[-1])


def test_matches_are_plain_alignments(spark):
    """Planted, edited and cut templates: found or not, and covered, as an alignment without index and band says."""
    rng = np.random.default_rng(12)
    templates = {f"T{i}": (" ".join(f"w{x}" for x in rng.integers(0, 400, int(rng.integers(8, 60)))),) for i in range(6)}
    scanner = licenses.Scanner(templates)
    texts_, want = [], []
    for i in range(60):
        name = f"T{i % 6}"
        body = templates[name][0].split()
        part = body[: int(len(body) * (1.0, 0.9, 0.6, 0.4)[i % 4])]
        for _ in range(i % 3):
            part[int(rng.integers(len(part)))] = "changed"
        if i % 5 == 0:
            part.insert(len(part) // 2, "added")
        noise = [f"n{x}" for x in rng.integers(0, 10**6, 80)]
        texts_.append(" ".join(noise[:30] + part + noise[30:]))
        want.append((name, plain_alignment(noise[:30] + part + noise[30:], body)[1] / len(body)))
    df = spark.createDataFrame(list(enumerate(texts_)), "doc_id long, text string")
    got = defaultdict(list)
    for r in licenses.scan_licenses(df, templates).collect():
        got[r["doc_id"]].append(r)
    found = 0
    for i, (name, cover) in enumerate(want):
        if cover >= licenses.LEAST + 0.05:
            (r,) = got[i]
            assert r["license"] == name and abs(r["coverage"] - cover) < 0.03 and r["matched"] == (r["coverage"] >= licenses.COVERAGE), (i, r, cover)
            found += 1
    assert found > 50 and scanner.scan(" ".join(f"n{x}" for x in range(500))) == []


def test_alignment_bridges_edits():
    scan = licenses.Scanner(licenses.TEMPLATES)
    body = licenses.TEMPLATES["MIT"][3]
    words = body.split()
    words[10:11], words[60] = ["really", "any"], "nothing"
    text = "Intro line. " + " ".join(words) + " And more."
    (name, cover, start, end), *rest = scan.scan(text)
    assert name == "MIT" and 0.95 < cover < 1 and text[start:end].startswith("Permission") and text[start:end].endswith("SOFTWARE") and not rest
    assert scan.scan("Permission is hereby granted to nobody") == []
    assert scan.scan(None) == [] and scan.scan("") == []


# 4

def test_toxicity_ranks_and_keeps_to_its_rows(spark, docs, labels):
    used = toxicity.training_rows(docs, labels)
    assert used.filter(toxicity.held_out()).count() == 0
    words = ["idiot", "moron", "scum"]
    rng = np.random.default_rng(0)
    plain = lambda n: " ".join("".join(rng.choice(list("abcdeghklnrstuv"), rng.integers(2, 8))) for _ in range(n))
    data = [(plain(40) + (f" {words[i % 3]} {plain(5)} {words[(i + 1) % 3]}" if i % 3 == 0 else ""), int(i % 3 == 0)) for i in range(400)]
    score = toxicity.train([t for t, _ in data], [y for _, y in data]).scorer()
    new = [(plain(30) + " moron " + plain(3) + " idiot", 1) for _ in range(30)] + [(plain(33), 0) for _ in range(30)]
    s = [(score(t), y) for t, y in new]
    assert np.mean([a > b for a, x in s if x for b, y in s if not y]) > 0.95


def test_toxicity_rows_are_plain_pythons(spark, docs, labels, texts):
    """Every score is what the model gives the whole text alone; folds as zlib's crc32 has them; the sample keeps its bounds."""
    from zlib import crc32

    model = toxicity.fit(docs, labels)
    score = model.scorer()
    got = toxicity.classify(docs, labels).collect()
    assert {r["doc_id"] for r in got} == set(texts)
    for r in got:
        assert abs(r["score"] - score(texts[r["doc_id"]])) < 1e-12 and r["predicted"] == int(r["score"] >= 0.5)
        assert r["held_out"] == (crc32(str(r["doc_id"]).encode()) % 5 == 0)
    used = toxicity.training_rows(docs, labels, per_class=7, most=4000).collect()
    for c in (0, 1):
        own = [r for r in used if r["toxic"] == c]
        assert 0 < len(own) <= 7 and sum(len(r["text"].encode()) for r in own) <= 4000
    twice = docs.unionByName(docs)
    assert toxicity.training_rows(twice, labels).count() == toxicity.training_rows(docs, labels).count()


def test_toxicity_of_odd_rows(spark, odd, labels):
    got = toxicity.classify(odd, no_labels(spark)).collect()
    assert len(got) == odd.count() and {r["score"] for r in got} == {0.0} and not any(r["predicted"] for r in got)
    assert all(0 <= r["score"] <= 1 for r in toxicity.scores(odd, toxicity.train(["bad bad scum", "fine day"] * 30, [1, 0] * 30)).collect())
    assert toxicity.classify(empty(odd), labels).count() == 0


# 5

def test_base_spans_consume_failed_matches():
    assert secrets.base_spans("secret: token: abcdefg") == []
    assert secrets.base_spans("PassWord = \"abc123\"") == [(0, 18, "assign")]
    assert secrets.base_spans("xAKIA" + "A1" * 8 + " AKIAB") == [(1, 21, "access")]
    assert secrets.base_spans("é" + "0a" * 12) == [(1, 25, "hex")]
    assert [k for _, _, k in secrets.base_spans("token=" + "ab12" * 6)] == ["assign", "hex"]


def test_weak_parts_need_their_complements():
    weak = "aB3dE5gH7jK9mN1pQ3sT5"
    assert secrets.scan(f"note {weak} here")[1] == []
    _, spans = secrets.scan(f"client_id: robot7\nvalue {weak}\n")
    assert {k for _, _, k in spans} == {"weak_id", "weak_secret"}
    assert secrets.scan(f"client_id: robot7\n\n value {weak}\n")[1] == []  # another scope
    assert secrets.scan(f"client_id: robot7 {'x ' * 150}{weak}")[1] == []  # out of reach
    text = f"login=bob https://db.example.com/x {weak}"
    assert {k for _, _, k in secrets.scan(text)[1]} == {"weak_id", "weak_secret", "weak_endpoint"}
    assert weak not in secrets.redact(text) and secrets.redact("plain") == "plain" and secrets.redact(None) is None


def test_secret_parts_have_no_longest(spark):
    """Long parts are reported whole, and parts of one paragraph are linked however far apart, by the rows and the redaction."""
    weak = "aB3dE5gH7jK9mN1pQ3sT5"
    token, url, name = (weak * 15)[:300], "https://db.example.com/" + "x/" * 250, "n" * 300
    made = [f"client_id: robot7 value {token} end", f"login={name} {url} {weak}", f"client_id: robot7 {'x ' * 3000}{weak} end", f"client_id: robot7 {'x ' * 150}\n\n{weak} end"]
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    spans = {r["doc_id"]: r["spans"] for r in secrets.find_secrets(df).collect()}
    place = lambda i, part, kind: f"{kind}:{made[i].index(part)}:{made[i].index(part) + len(part)}"
    assert spans[0] == ",".join([place(0, "robot7", "weak_id"), place(0, token, "weak_secret")])
    assert spans[1] == ",".join([place(1, name, "weak_id"), place(1, url, "weak_endpoint"), place(1, weak, "weak_secret")])
    assert spans[2] == ",".join([place(2, "robot7", "weak_id"), place(2, weak, "weak_secret")])
    assert spans[3] == ""
    kept = {r["doc_id"]: r["text"] for r in secrets.redacted(df).collect()}
    assert kept[0] == "client_id: [SECRET] value [SECRET] end" and kept[1] == "login=[SECRET] [SECRET] [SECRET]"
    assert weak not in kept[2] and kept[3] == made[3]


def test_secret_rows_are_plain_pythons(spark, docs, texts, odd):
    assign = re.compile(r"""(password|passwd|secret|token|api_?key)["']? *[:=] *["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
    got = {r["doc_id"]: r for r in secrets.find_secrets(docs).collect()}
    for d, t in texts.items():
        s = [(m.start(), 0, m.end()) for m in assign.finditer(t) if len(m[2]) >= 6] + [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20] + [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24]
        line = ",".join(f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in sorted(s))
        assert got[d]["base_sha256"] == hashlib.sha256(line.encode()).hexdigest()
    assert secrets.find_secrets(odd).count() == odd.count() and secrets.redacted(odd).columns == odd.columns
    assert secrets.find_secrets(empty(odd)).count() == 0


# 6

def test_fingerprints_and_neighbours(spark, odd):
    rows = [(i * 1000 if i % 3 else i, f"Line {i}. Same here, and there.\nTail {i % 4}.\n\nNext section {i // 5}.") for i in range(700)] + [(5_000_000_000, "far away. from all")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r for r in merkle.fingerprints(df).collect()}
    order = sorted(rows, reverse=True)
    for i, (d, t) in enumerate(order):
        nxt = order[(i + 1) % len(order)][1]
        edited = t[: len(t) - len(t) // 2] + nxt[: len(t) // 2]
        assert (got[d]["n_chars"], got[d]["edited_sha256"]) == (len(t), hashlib.sha256(edited.encode()).hexdigest())
    by_text = defaultdict(set)
    for d, t in rows:
        by_text[t].add(got[d]["fingerprint"])
    assert all(len(v) == 1 for v in by_text.values()) and len({next(iter(v)) for v in by_text.values()}) == len(by_text)
    again = merkle.fingerprints(odd).collect()
    assert len(again) == odd.count() and all(0 <= r["near_edited"] <= 1 and 0 <= r["near_next"] <= 1 for r in again)
    assert merkle.fingerprints(empty(odd)).count() == 0


def test_edits_are_located(spark):
    seven = "\n\n".join(f"Part {i} one.\nPart {i} two." for i in range(7))
    rows = [("A one.\nA two.\n\nB one.\nB two.", "A one.\nA two.\n\nB one.\nB 2.\nB three.")] * 2 + [("same", "same"), ("", "x"), (seven, "New one.\n\n" + seven), (seven, seven.replace("Part 3 two", "Part 3 2")), ("a\n\nb\n\nb", "a\n\nb"), (None, "")]
    got = [[tuple(c) for c in r["changed"]] for r in merkle.edits(spark.createDataFrame(rows, "old string, new string")).collect()]
    assert got[:2] == [[("old", 1, 1), ("new", 1, 1), ("new", 1, 2)]] * 2
    assert got[2] == [] and got[3] == [("old", 0, 0), ("new", 0, 0)] and got[7] == []
    assert got[4] == [("new", 0, 0)] and got[5] == [("old", 3, 1), ("new", 3, 1)]
    assert got[6] and {c[0] for c in got[6]} <= {"old", "new"}
    assert merkle.nodes(spark.createDataFrame(rows[:1], "text string, new string").select(F.lit(1).alias("doc_id"), "text")).count() == 4


def plain_tree(text, kept=merkle.KEPT):
    """(root, kept node hashes) of a text by plain Python."""
    xx = lambda c: f"{xxhash.xxh64_intdigest(c.encode(), 42):016X}"
    md5 = lambda hs: hashlib.md5("".join(hs).encode()).hexdigest()
    cut = lambda s, p: [x for x in re.split(p, s) if x is not None]
    ends = [m.end() for m in re.finditer(r"\n[ \t]*\n(?=[^\n])", text)]
    sections = [text[a:b] for a, b in zip([0, *ends], [*ends, len(text)], strict=True)]
    found, tops = set(), []
    for s in sections:
        inner = []
        for p in cut(s, r"(?<=\n)(?=[^\n])"):
            leaves = [xx(c) for c in cut(p, r"(?<=[.!?,;|*%&$#]\s)|(?<=[eoad]\s)")]
            if len(leaves) > 1 and leaves[-1] == xx("") and p:
                leaves = leaves  # a trailing empty chunk counts
            inner.append(md5(leaves))
            found |= {h[8:] for h in leaves} | {inner[-1][:8].upper()}
        tops.append(md5(inner))
        found.add(tops[-1][:8].upper())
    return md5(tops), sorted(found)[:kept]


def test_fingerprints_and_likeness_are_plain_pythons(spark, docs, texts):
    """Root, node hashes and likeness on ordinary documents, with blank lines that hold many blanks."""
    ids = sorted(texts)[:80]
    made = {i: texts[i] for i in ids} | {10**6: "One.\n" + " " * 40 + "\nTwo, too.\nThree.\n\n\nFour.", 10**6 + 1: "", 10**6 + 2: "\n\nabc"}
    df = spark.createDataFrame(list(made.items()), "doc_id long, text string")
    order = sorted(made, reverse=True)
    trees = {i: plain_tree(t) for i, t in made.items()}

    def like(x, y):
        if x[0] == y[0]:
            return 1.0
        both = sorted(set(x[1]) | set(y[1]))[: merkle.KEPT]
        return len([h for h in both if h in x[1] and h in y[1]]) / len(both)

    for r in merkle.fingerprints(df).collect():
        i = r["doc_id"]
        nxt = order[(order.index(i) + 1) % len(order)]
        n = len(made[i])
        edited = plain_tree(made[i][: n - n // 2] + made[nxt][: n // 2])
        assert r["fingerprint"] == (trees[i][0] + ":" + "".join(trees[i][1])).lower()
        assert r["edited_fingerprint"] == (edited[0] + ":" + "".join(edited[1])).lower()
        assert abs(r["near_edited"] - like(trees[i], edited)) < 1e-9 and abs(r["near_next"] - like(trees[i], trees[nxt])) < 1e-9


# 7

def brute_components(codes, budget=3):
    n = len(codes)
    i, j = np.triu_indices(n, 1)
    near = np.bitwise_count(codes[i] ^ codes[j]) <= budget
    return simhash.local_components(n, i[near], j[near])


def planted(rng, groups, members, most):
    out = []
    for b in rng.integers(0, 1 << 63, groups, dtype=np.uint64):
        for _ in range(members):
            x = int(b)
            for k in rng.choice(64, rng.integers(0, most), replace=False):
                x ^= 1 << int(k)
            out.append(x)
    return np.unique(np.array(out, np.uint64))


@pytest.mark.parametrize("hot", [200_000, 3])
def test_trie_links_span_the_components(spark, hot):
    codes = planted(np.random.default_rng(5), 40, 9, 5)
    want = brute_components(codes)
    df = spark.createDataFrame([(int(c),) for c in codes.view(np.int64)], "fp long")
    got = [(r["a"], r["b"]) for r in simhash.links(df, hot=hot).collect()]
    at = {int(c): i for i, c in enumerate(codes.view(np.int64))}
    e = np.array([(at[a], at[b]) for a, b in got], int).reshape(-1, 2)
    assert np.array_equal(simhash.local_components(len(codes), e[:, 0], e[:, 1]), want)


def test_a_dense_group_costs_no_square():
    rng = np.random.default_rng(1)
    base = int(rng.integers(0, 1 << 63))
    codes = np.unique(np.array([base ^ sum(1 << int(k) for k in rng.choice(64, 2, replace=False)) for _ in range(4000)], np.uint64))
    n = len(codes)
    label = simhash.trie_links(np.zeros(n, np.int64), codes, np.zeros(n, np.int64), 64, codes, 3)
    assert np.array_equal(label, brute_components(codes))


def test_fingerprints_of_words():
    assert simhash.shingle_hashes("A  b\tC d") == [xxhash.xxh64_intdigest(s, 42) for s in ("a b c", "b c d")]
    assert simhash.shingle_hashes("É Xx") == [xxhash.xxh64_intdigest("É xx", 42)]
    assert simhash.fingerprints_of([None, "", " \n"]).tolist() == [0, 0, 0]
    assert simhash.fingerprints_of(["one"])[0] == xxhash.xxh64_intdigest("one", 42)


def test_simhash_classes_are_brute_forces(docs, texts, odd):
    ids = sorted(texts)
    codes = simhash.fingerprints_of([texts[i] for i in ids])
    want = brute_components(codes)
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.summary(docs).collect()}
    assert got == {d: (format(int(codes[i]), "016x"), ids[want[i]]) for i, d in enumerate(ids)}
    out = simhash.summary(odd).collect()
    assert len(out) == odd.count() and {r["component_id"] for r in out if r["fingerprint"] == "0" * 16} == {1}
    kept = simhash.deduplicate(odd)
    assert kept.columns == odd.columns and sorted(r["doc_id"] for r in kept.collect() if r["doc_id"]) == [1, 3, 4, 7, 9]
    assert simhash.summary(empty(odd)).count() == 0


def brute_near_copies(texts):
    """Index of the first text of each text's group, by exact Jaccard of all pairs over five-word shingles."""
    sets = [frozenset(simhash.shingle_hashes(t, 5)) for t in texts]
    label = list(range(len(sets)))
    for i in range(len(sets)):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if (sets[i] == sets[j] or 5 * both >= 4 * (len(sets[i]) + len(sets[j]) - both)) and label[i] != label[j]:
                low, high = sorted((label[i], label[j]))
                label = [low if x == high else x for x in label]
    return label


@pytest.mark.parametrize("room", [jaccard.ROOM, 0])
def test_near_dedup_stage_keeps_one_of_each_near_copy(spark, sf, texts, monkeypatch, room):
    """Against brute force: copies on both sides of 0.8, chains, a group around one text, a line that all texts hold."""
    import corpus_pipeline

    monkeypatch.setattr(jaccard, "ROOM", room)
    rng = np.random.default_rng(3)
    word = lambda: f"w{rng.integers(5000)}"
    line = "this line stands in every one of these texts"
    made = [texts[i] for i in sorted(texts)[:60]] + [None, "", "one two", "ONE  two", "a b c d e", "a b c d e f"]
    for most in (0, 1, 1, 2, 2, 3, 4):
        t = [word() for _ in range(int(rng.integers(40, 160)))]
        made.append(" ".join(t))
        for _ in range(6):
            u = list(t)
            for _ in range(most):
                u[int(rng.integers(len(u)))] = word()
            made.append(" ".join(u))
            t = u if most == 1 else t
    made += [f"{line} {word()}" for _ in range(12)] + [f"{line} " + " ".join(word() for _ in range(30)) for _ in range(12)]
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string").repartition(3)
    want = brute_near_copies(made)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.near_copies(df).collect()}
    assert got == dict(enumerate(want)) and len(set(want)) < len(want) - 20
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_dedup_stage(spark, df, sf).collect()) == sorted(set(want))
    assert jaccard.deduplicate(df.filter("false")).count() == 0


def test_near_dedup_stage_joins_by_the_trie(spark, sf, monkeypatch):
    """With no candidates from the prefix filter, near copies are one document by the trie alone; others stay."""
    import corpus_pipeline

    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in rng.integers(0, 10**6, 3000)]
    near = [*base[:-1], "other"]
    made = [" ".join(base), " ".join(near), " ".join(f"w{i}" for i in rng.integers(0, 10**6, 300))]
    assert int(simhash.fingerprints_of(made[:1], 5)[0] ^ simhash.fingerprints_of(made[1:2], 5)[0]).bit_count() <= simhash.BUDGET
    monkeypatch.setattr(jaccard, "shared", lambda rows: rows.filter("false"))
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    assert sorted(r["doc_id"] for r in corpus_pipeline.near_dedup_stage(spark, df, sf).collect()) == [0, 2]


def test_near_dedup_stage_settles_a_wide_group_by_its_centre(spark, monkeypatch):
    """A group whose members lie on both sides of 0.8: few pairs are made for each row of a key, and brute force links the same."""
    rng = np.random.default_rng(11)
    word = lambda: f"w{rng.integers(10**6)}"
    base, made = [word() for _ in range(200)], []
    for i in range(150):
        t = list(base) if i % 5 else [*made[-1].split()[:100], *(word() for _ in range(90))] if i % 10 else list(base)
        for _ in range(int(rng.integers(1, 14))):
            t[int(rng.integers(len(t)))] = word()
        made.append(" ".join(t))
    monkeypatch.setattr(jaccard, "trie_parts", lambda marked: marked.selectExpr("node AS a", "node AS b").filter("false"))  # links pairs of less, too
    seen, pairs = [], jaccard._pairs
    monkeypatch.setattr(jaccard, "_pairs", lambda df, every: seen.append(df.count()) or pairs(df, every))
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string").repartition(3)
    want = brute_near_copies(made)
    assert {r["doc_id"]: r["component_id"] for r in jaccard.near_copies(df).collect()} == dict(enumerate(want))
    assert 10 < len(set(want)) < 140
    assert sum(seen) < 20 * len(made), seen


def test_near_dedup_stage_spreads_shared_differences_only(spark, monkeypatch):
    """Texts edited apart: a shingle that only one of them asks for makes no row."""
    rng = np.random.default_rng(13)
    word = lambda: f"w{rng.integers(10**6)}"
    base, made = [word() for _ in range(200)], []
    for _ in range(60):
        t = list(base)
        for at in rng.choice(200, 8, replace=False):
            t[int(at)] = word()
        made.append(" ".join(t))
    made += [f"{made[i]} {word()} {word()}" for i in range(0, 60, 6)]
    monkeypatch.setattr(jaccard, "trie_parts", lambda marked: marked.selectExpr("node AS a", "node AS b").filter("false"))
    rounds, rows, around, spread = [], [], jaccard.around, jaccard._spread
    monkeypatch.setattr(jaccard, "around", lambda *a: rounds.append(components.cut(around(*a))) or rounds[-1])
    monkeypatch.setattr(jaccard, "_spread", lambda *a: rows.append(components.cut(spread(*a))) or rows[-1])
    df = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string").repartition(3)
    got = {r["doc_id"]: r["component_id"] for r in jaccard.near_copies(df).collect()}
    assert got == dict(enumerate(brute_near_copies(made))) and len(set(got.values())) < len(made) - 9
    asked = sum(r.agg(F.sum(F.size("asks"))).first()[0] for r in rounds)
    made_rows = sum(r.count() for r in rows if "x" in r.columns)
    assert asked > 1000 and made_rows < asked * 2 / 3, (asked, made_rows)


def test_difference_finds_every_pair():
    """Of two sets of 0.8 or more, one near the centre is found by a shingle that the other asks for, if they are not both alike to it."""
    rng = np.random.default_rng(4)
    hits, late, rank = 0, np.arange(0, 10**6, 3, dtype=np.uint64), rng.permutation(10**6 // 3 + 1)
    for _ in range(3000):
        centre = rng.choice(10**6, int(rng.integers(1, 60)), replace=False).astype(np.uint64)

        def edited(x, most):
            x = x[rng.random(len(x)) >= rng.random() * most]
            return np.unique(np.r_[x, rng.choice(10**6, int(rng.random() * most * len(centre)) + 1).astype(np.uint64)])

        x = edited(centre, 0.7)
        y = edited(x, 0.25)
        (xl, xn, _, xf, xa), (yl, yn, _, yf, ya) = (jaccard.difference(s, np.sort(centre), late, rank) for s in (x, y))
        both = len(np.intersect1d(x, y))
        if 5 * both < 4 * (len(x) + len(y) - both) or (xl and yl):
            continue
        if yn and not xl:
            hits += 1
            assert len(np.intersect1d(xa, yf))
        if xn and not yl:
            hits += 1
            assert len(np.intersect1d(ya, xf))
    assert hits > 300


def test_components_of_a_small_graph_take_one_task(spark):
    """With and without rounds the roots are the same; loops, repeats and an empty graph are taken."""
    rng = np.random.default_rng(6)
    pairs = [(int(a) - 300, int(b) - 300) for a, b in rng.integers(0, 600, (250, 2))] + [(i, i + 1) for i in range(1000, 1100)] + [(5, 5), (1001, 1000)]
    edges = spark.createDataFrame(pairs, "a long, b long").repartition(5)
    roots = lambda few: {r["node"]: r["root"] for r in components.components(edges, few).collect()}
    seen = []
    want = roots(0)
    assert len(want) > 200 and roots(10**6) == want and roots(len(pairs) - 60) == want
    assert components.components(edges.filter("false"), 100).count() == 0
    stage = spark.sparkContext._jsc.sc().dagScheduler().nextStageId
    for few in (0, 10**6):
        began = stage()
        components.components(edges, few).count()
        seen.append(stage() - began)
    assert seen[1] < seen[0] / 3, seen


def test_components_of_a_long_path(spark):
    edges = spark.range(300).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b")).unionByName(spark.createDataFrame([(1000, 1001), (1001, 1000), (7, 7)], "a long, b long"))
    got = {r["node"]: r["root"] for r in components.components(edges).collect()}
    assert got == {**{i: 0 for i in range(1, 301)}, 1001: 1000}


# 8

@pytest.fixture(scope="module")
def weights():
    return htmltext.train(*htmltext.training_set(250, 3), epochs=10, seed=3)


def test_parser_blocks():
    page = "<html><head><title>T</title><script>var a='<p>x</p>';</script></head><body><nav><ul><li>One<li>Two</ul></nav><!-- c --><article><h1>A &amp; B</h1><p><b>First\n  line<br>more<p>Second &am</article>tail"
    assert [b[0] for b in htmltext.blocks_of(page)] == ["One", "Two", "A & B", "First line more", "Second &am", "tail"]
    assert htmltext.blocks_of(None) == htmltext.blocks_of("") == htmltext.blocks_of("<script>x") == []
    assert [b[0] for b in htmltext.blocks_of("<![if x]>a<p>b")] == ["a", "b"] or htmltext.blocks_of("<![if x]>a<p>b")


def test_parser_goes_on_behind_malformed_sections():
    for section in ("<![foo bar]>", "<![ x>", "<![>", "<![if x>", "<![temp y>", "<![if !IE]>"):
        assert [b[0] for b in htmltext.blocks_of(f"<p>a</p>{section}<p>b</p><p>c</p>")] == ["a", "b", "c"]


def test_block_figures_are_of_the_whole_block():
    """The 41st word on and the 401st character on count."""
    short, long = ("a " * 40).strip(), ("a " * 200).strip()
    p = htmltext.path_mask((("p", ()),))
    one, two = (htmltext.vectors([(t, p, 0.0)])[0] for t in (long + " b" * 40, long + " 1" * 40))
    assert (one != two).sum() >= 2 and htmltext.vectors([(short, p, 0.0)]).shape == (1, htmltext.INPUT)


def test_formulas_stay_in_their_line():
    page = "<article><p>Let <math><mi>x</mi><mo>=</mo><mn>2</mn><annotation>x=2</annotation></math> hold.</p><p>A <svg><title>t</title><text>mark</text></svg> here<noscript> too</noscript></p><iframe>gone</iframe></article>"
    assert [b[0] for b in htmltext.blocks_of(page)] == ["Let x=2 hold.", "A mark here", "too"]


def test_deep_pages_cost_no_square():
    """Tags in tags: many levels, end tags of nothing, list items under deep parts."""
    from time import perf_counter

    def took(n):
        page = "".join(f"<div class='c{i % 9}'>t{i}" for i in range(n)) + "<li>x" * n + "</b></u>" * n + "</div>" * n
        t = perf_counter()
        blocks = htmltext.blocks_of(page)
        htmltext.vectors(blocks)
        assert [b[0] for b in blocks[: n + 1]] == [f"t{i}" for i in range(n)] + ["x"] and len(blocks) == 2 * n
        return perf_counter() - t

    took(100)
    small = took(2_500)
    assert took(20_000) < 20 * small + 1


def test_path_inputs():
    a = htmltext.path_mask((("html", ()), ("body", ()), ("div", ("post",)), ("b", ()), ("p", ())))
    bits = {htmltext._bucket(k, v, htmltext.PATH_DIM) for k, v in (("t", "div"), ("n", "post"), ("t", "p"), ("leaf", "p"))}
    assert {i for i in range(htmltext.PATH_DIM) if a >> i & 1} == bits


def test_labeller_on_new_pages(weights):
    rng, right, n = np.random.default_rng(77), 0, 0
    for _ in range(60):
        page, truth = htmltext.sample_page(rng)
        blocks = htmltext.blocks_of(page)
        if [b[0] for b in blocks] == [t for _, t in truth]:
            p = htmltext.probabilities([htmltext.vectors(blocks)], weights)[0] >= 0.5
            right, n = right + (p == np.array([m for m, _ in truth])).sum(), n + len(truth)
    assert right / n > 0.95


def test_lstm_gradient():
    rng = np.random.default_rng(0)
    w = {k: v.astype(float) for k, v in htmltext.init_weights(rng).items()}
    x, mask = rng.random((5, 2, htmltext.INPUT)), np.ones((5, 2))
    mask[3:, 1] = 0
    loss = lambda u: float((htmltext._run(x, mask, w["wf"], u, w["bf"])[0].astype(float) ** 2).sum())
    out, trace = htmltext._run(x, mask, w["wf"], w["uf"], w["bf"], True)
    _, du, _ = htmltext._back(x, 2 * out, trace, w["uf"])
    for i, j in ((0, 0), (3, 50), (20, 90)):
        e = np.zeros_like(w["uf"])
        e[i, j] = 1e-2
        assert abs((loss(w["uf"] + e) - loss(w["uf"] - e)) / 2e-2 - du[i, j]) < 2e-2 * max(1, abs(du[i, j]))


def test_pages_give_their_articles(spark, sf, weights):
    pages = spark.read.parquet(f"{sf}/pages.parquet")
    got = {r["page_id"]: r for r in htmltext.main_text(pages, weights).collect()}
    good = 0
    for r in pages.collect():
        body = r["html"][r["html"].find("<article>") : r["html"].find("</article>")]
        lines = [re.sub(r"\s+", " ", htmltext.entities.unescape(re.sub("<[^>]+>", "", s))).strip() for s in re.split(r"<(?:h1|/h1|p|/p|br|article)>", body)]
        good += "\n".join(s for s in lines if s) == got[r["page_id"]]["text"]
        assert got[r["page_id"]]["n_chars"] == len(got[r["page_id"]]["text"])
    assert good >= 0.9 * pages.count()
    odd = spark.createDataFrame([(1, None, None), (None, "u", ""), (3, "u", "<p>")], "page_id long, url string, html string")
    assert {(r["text"], r["n_chars"]) for r in htmltext.main_text(odd, weights).collect()} == {("", 0)}
    assert htmltext.main_text(empty(odd), weights).count() == 0


# 9

@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(queries.word_vocabulary())


SPECIAL = ["", "a", "İstanbul ΑΣ Σ ΣΑΣ.", "don't we'll I'M x<|endoftext|>yz <|startoftext|>", "aaaa bbbbb llll ciónllllue", "\x1c a\x1fb", "é café ½ ² 123 漢字 \U0001f914!!!...", "hello" * 400, "<|ENDOFTEXT|> <|", "x y\x85z　w"]


def test_tokens_are_the_librarys(texts, library):
    mine = bpe.Tokenizer(queries.word_vocabulary())
    for t in [*SPECIAL, *list(texts.values())[:120]]:
        ids = library.encode(t, add_special_tokens=False).ids
        assert mine.encode(t) == ids and mine.decode(ids) == library.decode(ids, skip_special_tokens=False)


def test_automaton_accepts_only_merged_sequences():
    vocab = {s: i for i, s in enumerate(["a", "b", "c", "aa", "ab", "aab", "bc"])}
    merges = [("a", "a"), ("a", "b"), ("a", "ab"), ("b", "c")]
    auto = bpe.Automaton(vocab, merges)

    def plain(word):
        w = list(word)
        for a, b in merges:
            out, i = [], 0
            while i < len(w):
                if i + 1 < len(w) and (w[i], w[i + 1]) == (a, b):
                    out.append(a + b)
                    i += 2
                else:
                    out.append(w[i])
                    i += 1
            w = out
        return w

    from itertools import product

    for n in range(1, 8):
        for word in product("abc", repeat=n):
            ids = auto.encode(list(word))
            assert [auto.labels[i] for i in ids] == plain(word) and auto.merged(list(word)) == ids
            assert all(auto.allowed(a, b) == auto._find(a, b) for a, b in zip(ids, ids[1:], strict=False))


def test_a_word_without_a_path_is_merged():
    """The only way to abc begins with a token that another merge takes apart first."""
    vocab = {s: i for i, s in enumerate(["a", "b", "c", "bc", "ab", "abc"])}
    auto = bpe.Automaton(vocab, [("b", "c"), ("a", "b"), ("ab", "c")])
    assert [auto.labels[i] for i in auto.encode(list("abc"))] == ["a", "bc"]
    auto.ends = [-1] * len(auto.ends)
    assert [auto.labels[i] for i in auto.encode(list("ababc"))] == ["ab", "a", "bc"]


def test_bpe_rows(spark, odd, library):
    path = queries.word_vocabulary()
    got = bpe.digests(odd, path).collect()
    assert len(got) == odd.count()
    for r, t in zip(sorted(got, key=lambda r: (str(r["doc_id"]), r["n_tokens"])), sorted(((x["doc_id"], x["text"] or "") for x in odd.collect()), key=lambda x: (str(x[0]), len(library.encode(x[1], add_special_tokens=False).ids))), strict=True):
        ids = library.encode(t[1], add_special_tokens=False).ids
        assert (r["n_tokens"], r["ids_sha256"]) == (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest())
    both = bpe.decode(bpe.encode(odd, path), path)
    assert both.filter("text is null and (size(ids) > 0 or decoded != '')").count() == 0
    assert bpe.digests(empty(odd), path).count() == 0


def test_memo_gives_up_the_older_half():
    made = []
    m = bpe.Memo(lambda k: made.append(k) or k, 4)
    assert [m[k] for k in "abcab"] == list("abcab") and len(m) <= 2 and made == list("abc")


# 10

def brute_repeats(rows, length):
    where = Counter(b[i : i + length] for b in rows for i in range(len(b) - length + 1))
    out = []
    for b in rows:
        gone = np.zeros(len(b), bool)
        for i in range(len(b) - length + 1):
            if where[b[i : i + length]] > 1:
                gone[i : i + length] = True
        out.append((len(b), int(gone.sum()), int((np.diff(np.r_[0, gone.astype(int)]) == 1).sum()), hashlib.sha256(bytes(x for x, g in zip(b, gone) if not g)).hexdigest()))
    return out


def test_repeats_are_brute_forces(spark, texts, monkeypatch):
    rng = np.random.default_rng(2)
    some = ["".join(rng.choice(list("abé "), 120)) for _ in range(6)]
    rows = [some[0], some[0], some[0][:70] + some[1], some[1][30:] + some[2][:60], "ab" * 90, "x" * 150, some[3] + some[3], some[4], "", None, some[5][:40] + some[4][50:] + some[5], "短い"]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").repartition(3)
    monkeypatch.setattr(suffix_dedup, "FLUSH_BYTES", 300)
    got = {r[0]: tuple(r)[1:] for r in suffix_dedup.summary(df, 40).collect()}
    assert got == dict(enumerate(brute_repeats([(t or "").encode() for t in rows], 40)))
    ids = sorted(texts)
    df = spark.createDataFrame([(i, texts[i]) for i in ids], "doc_id long, text string")
    got = {r[0]: tuple(r)[1:] for r in suffix_dedup.summary(df).collect()}
    assert got == dict(zip(ids, brute_repeats([texts[i].encode() for i in ids], 200), strict=True))


def test_equal_contexts_are_found_exactly():
    rng = np.random.default_rng(6)
    base_ = rng.integers(97, 100, 400).astype(np.uint8)
    flat = np.concatenate([base_, base_, np.full(3000, 97, np.uint8), base_[:200], rng.integers(97, 100, 200).astype(np.uint8)])
    _, _, _, _, count, at = suffix_dedup.contexts_of([flat.tobytes()], 40)
    wide = count + 39
    first = suffix_dedup.equals(flat, at, wide, 40, room=1000)
    seen: dict[bytes, int] = {}
    assert first.tolist() == [seen.setdefault(flat[a : a + w].tobytes(), i) for i, (a, w) in enumerate(zip(at.tolist(), wide.tolist(), strict=True))]


def test_one_seed_everywhere_is_dealt_once_a_portion(spark):
    """A line in very many texts and a long run of one byte: what is dealt does not grow with the places."""
    line = "".join(np.random.default_rng(8).choice(list("abcdefgh "), 260))
    df = spark.range(100_000).select(F.col("id").alias("doc_id"), F.concat(F.lit(line), F.lit(" "), F.col("id").cast("string")).alias("text")).repartition(8)
    dealt = suffix_dedup.deal(df, 8).filter("data is not null").agg(F.sum(F.length("data") + F.length("meta"))).first()[0]
    assert dealt < 0.1 * 100_000 * len(line)  # what is left are the strings that run on into the number
    got = suffix_dedup.summary(df).agg(F.min("n_removed"), F.max("n_removed"), F.max("n_spans"), F.count("*")).first()
    assert got[0] >= 260 and got[1] <= 267 and got[2] == 1 and got[3] == 100_000


def test_long_runs_and_portions(spark, monkeypatch):
    run = spark.createDataFrame([(1, "z" * 5_000_000 + "end"), (2, "q" * 150 + "r")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in suffix_dedup.summary(run).collect()}
    assert (got[1]["n_removed"], got[1]["n_spans"], got[2]["n_removed"]) == (5_000_000, 1, 0)
    rng = np.random.default_rng(9)
    some = "".join(rng.choice(list("abc "), 900))
    rows = [some, some[300:] + "x" + some[:200], "ab" * 400, some]
    monkeypatch.setattr(suffix_dedup, "FLUSH_BYTES", 130)
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string")
    got = {r[0]: tuple(r)[1:] for r in suffix_dedup.summary(df, 40).collect()}
    assert got == dict(enumerate(brute_repeats([t.encode() for t in rows], 40)))


def test_repeats_of_odd_rows(spark, odd):
    got = suffix_dedup.summary(odd).collect()
    assert len(got) == odd.count()
    by = {r["doc_id"]: r for r in got if r["doc_id"]}
    assert by[1]["n_removed"] == 0 and by[7]["n_removed"] == by[7]["n_bytes"] and by[8]["n_bytes"] - by[8]["n_removed"] <= 200
    assert suffix_dedup.remove(odd).columns == odd.columns
    assert suffix_dedup.summary(empty(odd)).count() == 0
    with pytest.raises(ValueError):
        suffix_dedup.repeated_starts([[(np.zeros(9, np.uint8), 1)]], 9)


# The pipeline

def test_pipeline_stages(spark, sf, docs, tmp_path):
    import corpus_pipeline

    seen, now = [docs.count()], docs
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, sf)
        if i < len(corpus_pipeline.STAGES) - 1:
            assert out.columns == docs.columns
        out.write.parquet(str(tmp_path / name))
        now = spark.read.parquet(str(tmp_path / name))
        seen.append(now.count())
    assert seen == sorted(seen, reverse=True) and seen[-1] > 0.5 * seen[0]
    assert now.filter("n_tokens != size(ids)").count() == 0
    assert corpus_pipeline.run(spark, sf).count() == seen[-1]


def test_checkpoint_folder_is_shared(spark):
    base.ensure_checkpoint_dir(spark)
    assert spark.sparkContext._jsc.sc().getCheckpointDir().isDefined()
