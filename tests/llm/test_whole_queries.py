"""Whole registered queries against plain Python on small tables."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from tests.llm import brute

import __spark_entry__ as entry
import corpus_pipeline
from levelgraph.llm import decontamination, learning, licences, line_quality, mixing, pii, quality_rules, text, token_counts, token_output

SOME = 40


@pytest.fixture(scope="module")
def texts(spark, tiny):
    return {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text").collect()}


def answers(spark, tiny, name):
    return {r["doc_id"]: r for r in entry.queries()[name](spark, tiny).collect()}


def test_token_output(spark, tiny, texts):
    from tokenizers import Tokenizer

    tok, at, got = Tokenizer.from_file(token_output.default_tokenizer()), 0, answers(spark, tiny, "op3_token_output")
    for i in sorted(texts):
        ids = np.array(tok.encode(texts[i] or "", add_special_tokens=False).ids + [2], dtype="<u4")
        r = got.pop(i)
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    assert not got


def test_token_counts(spark, tiny, texts):
    vocabulary = token_counts.load_vocabulary(token_counts.default_vocabulary())
    low = min(vocabulary.values()) - 10.0
    longest = max(map(len, vocabulary))

    def pieces(word):
        s, best = token_counts.MARK + word, [(0.0, 0)]
        for end in range(1, len(s) + 1):
            n = len(s[end - 1].encode())
            options = [(best[end - 1][0] + n * low, -(best[end - 1][1] + n))]
            options += [(best[b][0] + vocabulary[s[b:end]], -(best[b][1] + 1)) for b in range(max(0, end - longest), end) if s[b:end] in vocabulary]
            score, count = max(options)
            best.append((score, -count))
        return best[-1][1]

    got, known = answers(spark, tiny, "op4_token_counts"), {}
    assert set(got) == set(texts)
    for i in sorted(texts)[:SOME]:
        ws = brute.words(texts[i])
        for w in ws:
            if w not in known:
                known[w] = pieces(w)
        assert (got[i]["n_pretokens"], got[i]["n_tokens"]) == (len(ws), sum(known[w] for w in ws))


def test_quality_rules(spark, tiny, texts):
    got = answers(spark, tiny, "op6_quality_rules")
    assert set(got) == set(texts)
    for i, t in texts.items():
        ws, t = brute.words(t), t or ""
        lines = [x for x in t.split("\n") if brute.words(x)]
        c = Counter(zip(ws, ws[1:], ws[2:]))
        cover = {k + d for k in range(len(ws) - 2) if c[tuple(ws[k : k + 3])] > 1 for d in range(3)}
        r = got[i]
        want = (len(ws), sum(map(len, ws)), sum(ch in "#*$%&|<>" for ch in t), len(lines) - len(set(lines)), len(cover))
        assert tuple(r[k] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == want
        failed = len(ws) < 50 or 100 * len(cover) > 50 * len(ws)
        assert r["base_failed"] == failed and r["kept"] == (not failed and r["score"] >= quality_rules.KEEP_AT)


def test_line_quality_scores(spark, tiny, texts):
    """Document scores from forward-backward sums in plain floating point, one document after the other."""
    docs, labels = spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{tiny}/labels.parquet")
    model = line_quality.fit(docs, labels)
    got = answers(spark, tiny, "op7_line_quality")
    gg, bb, gb = (np.exp(x) for x in model.stay)
    for i in sorted(texts)[:SOME]:
        lines = line_quality.read_lines(pa.array([texts[i]]))
        odds = np.exp(line_quality.with_neighbours(lines.own, lines.first) @ model.weights.astype(np.float32)).astype(float)
        n, share = len(odds), 1.0
        if n:
            f, b = np.zeros((n, 2)), np.ones((n, 2))
            f[0] = 1, odds[0]
            f[0] /= f[0].sum()
            for k in range(1, n):
                f[k] = f[k - 1, 0] * gg + f[k - 1, 1] * gb, (f[k - 1, 0] * gb + f[k - 1, 1] * bb) * odds[k]
                f[k] /= f[k].sum()
            for k in range(n - 2, -1, -1):
                b[k] = b[k + 1, 0] * gg + b[k + 1, 1] * odds[k + 1] * gb, b[k + 1, 0] * gb + b[k + 1, 1] * odds[k + 1] * bb
                b[k] /= b[k].sum()
            bad = f[:, 1] * b[:, 1] / (f * b).sum(axis=1)
            share = float((bad * lines.length).sum() / lines.length.sum())
        assert got[i]["n_lines"] == n and got[i]["bad_share"] == pytest.approx(share, abs=1e-4)
        assert got[i]["score"] == pytest.approx(float(learning.sigmoid(np.array([model.slope * share + model.shift]))[0]), abs=1e-3)


def test_licences(spark, tiny, texts):
    word, got = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"), answers(spark, tiny, "op8_licences")
    labels = {tuple(p.split()): label for p, label in licences.BASE}
    for i, t in texts.items():
        ws = word.findall((t or "").translate(brute.LOWER))
        places = [(k, label) for p, label in labels.items() for k in range(len(ws) - len(p) + 1) if tuple(ws[k : k + len(p)]) == p]
        r, starts = got.pop(i), [k for k, _ in places]
        base = sorted({label for _, label in places})
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (len(ws), len(places), min(starts, default=None), max(starts, default=None), ",".join(base))
        found = r["labels"].split(",") if r["labels"] else []
        assert found == sorted(set(found)) and set(base) <= set(found) and 0 <= r["score"] <= 1
        joined = f" {' '.join(ws)} "
        assert all(any(f" {phrase} " in joined for label, _, phrase in licences.TEMPLATES if label == x) for x in found if x not in base)
    assert not got


def _luhn(digits):
    total = 0
    for k, d in enumerate(map(int, reversed(digits))):
        total += d if k % 2 == 0 else (2 * d - 9 if 2 * d > 9 else 2 * d)
    return total % 10 == 0


def personal(t):
    """Base spans by the plain expressions."""
    out = []
    digits = lambda s: re.sub("[^0-9]", "", s)
    rules = (
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda s: all(int(p) <= 255 for p in s.split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda s: 14 <= len(digits(s)) <= 19 and _luhn(digits(s))), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda s: 10 <= len(digits(s)) <= 15),
    )
    for rank, (kind, expression, fits) in enumerate(rules):
        out += [(m.start(), rank, m.end(), kind) for m in re.finditer(expression, t or "") if fits(m.group())]
    return sorted(out)


def test_personal_data(spark, tiny, texts):
    got = answers(spark, tiny, "op10_personal_data")
    for i, t in texts.items():
        r, want = got.pop(i), personal(t)
        listed = [f"{kind}:{a}:{b}" for a, _, b, kind in want]
        assert r["base_sha256"] == hashlib.sha256(",".join(listed).encode()).hexdigest()
        assert [r[f"n_{k}"] for k in ("email", "ip", "card", "phone")] == [sum(x[3] == k for x in want) for k in ("email", "ip", "card", "phone")]
        spans = r["spans"].split(",") if r["spans"] else []
        assert set(listed) <= set(spans) and [int(s.split(":")[1]) for s in spans] == sorted(int(s.split(":")[1]) for s in spans)
    assert not got


def leaks(texts, items, at=0.5):
    """Every document aligned with every item, by a plain table of scores."""
    read = lambda t: [int(h) for h in decontamination._read(pa.array([t]))[0]]
    items = {i: read(t) for i, t in items.items() if t}
    out = set()
    for d, t in texts.items():
        words = np.array(read(t), dtype=np.uint64) if t else np.empty(0, np.uint64)
        held = set(words.tolist())
        for i, item in items.items():
            if item and sum(w in held for w in item) >= at * len(item) and decontamination.align(np.array(item, dtype=np.uint64), words)[0] >= at * 2 * len(item) - 1e-9:
                out.add((d, i))
    return out


def test_decontamination(spark, tiny, texts):
    items = {r["item_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()}
    got = {(r["doc_id"], r["item_id"]) for r in entry.queries()["op9_decontamination"](spark, tiny).collect()}
    assert got == leaks(texts, items)


def test_alignment_against_a_full_table():
    rng = np.random.default_rng(8)
    for _ in range(60):
        a, b = rng.integers(0, 6, rng.integers(1, 12)), rng.integers(0, 6, rng.integers(1, 40))
        h = np.zeros((len(a) + 1, len(b) + 1), dtype=int)
        for i in range(1, len(a) + 1):
            for j in range(1, len(b) + 1):
                h[i, j] = max(0, h[i - 1, j - 1] + (2 if a[i - 1] == b[j - 1] else -1), h[i - 1, j] - 1, h[i, j - 1] - 1)
        score, lo, hi = decontamination.align(a, b)
        assert score == h.max() and (not score or (0 <= lo < hi <= len(b) and decontamination.align(a, b[lo:hi])[0] == score))


def test_pipeline(spark, tiny, texts):
    """run() stage by stage: scores, pairs, alignments, sorted draws and whole-text encoding in plain Python."""
    from tokenizers import Tokenizer

    rows = {r["doc_id"]: r for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()}
    docs, labels = spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{tiny}/labels.parquet")
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    result = corpus_pipeline.run(spark, tiny).collect()
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before
    model = line_quality.fit(docs, labels)
    good = [i for i, t in texts.items() if model.score(model.bad_share(line_quality.read_lines(pa.array([t]))))[0] >= line_quality.PREDICT_AT]
    groups = brute.near_groups([(i, texts[i]) for i in good])
    kept = [i for i in good if groups[i][1] == i]
    items = {r["item_id"]: r["text"] for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()}
    leaked = {d for d, _ in leaks({i: texts[i] for i in kept}, items)}
    clean = [i for i in kept if i not in leaked]
    from tests.llm.test_operators import mixed_by_hand

    sized = [(i, len(brute.words(texts[i])), rows[i]["source"]) for i in clean]
    mixed = {r["source"]: r["target"] for r in mixing.mix(spark.createDataFrame([(i, texts[i], rows[i]["source"]) for i in clean], "doc_id long, text string, source string")).collect()}
    copies = mixed_by_hand(sized, mixed)
    tok, at, want = Tokenizer.from_file(token_output.default_tokenizer()), 0, []
    for i in sorted(clean):
        ids = np.array(tok.encode(texts[i] or "", add_special_tokens=False).ids + [2], dtype="<u4")
        for _ in range(copies[i]):
            want.append((i, at, len(ids), zlib.crc32(ids.tobytes())))
            at += len(ids)
    assert sorted((r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in result) == sorted(want)
    assert 0 < len(clean) < len(kept) < len(good) < len(texts)


def test_very_long_texts(spark):
    """A text of some megabytes and one of a single endless word, beside an empty one, through the scoring operators."""
    long = "alpha beta gamma delta. " * 120_000
    d = spark.createDataFrame([(1, long), (2, "x" * 300_000), (3, ""), (4, None)], "doc_id long, text string")
    rules = {r["doc_id"]: r for r in quality_rules.apply_rules(d).collect()}
    assert rules[1]["n_words"] == 480_000 and rules[2]["word_chars"] == 300_000 and rules[3]["n_words"] == rules[4]["n_words"] == 0
    counts = {r["doc_id"]: r for r in token_counts.count_tokens(spark.createDataFrame([(1, long), (3, "")], "doc_id long, text string")).collect()}
    assert counts[1]["n_pretokens"] == 480_000
    found = {r["doc_id"]: r for r in licences.scan_licences(d).collect()}
    assert found[1]["n_words"] == 480_000 and found[2]["n_words"] == 1
    assert decontamination.find_leaks(d, spark.createDataFrame([(7, "delta alpha beta gamma delta")], "item_id long, text string")).collect()[0]["doc_id"] == 1
    assert {r["doc_id"] for r in pii.find_personal_data(d).collect()} == {1, 2, 3, 4}
    assert text.words(pa.array([long])).counts.tolist() == [480_000]
