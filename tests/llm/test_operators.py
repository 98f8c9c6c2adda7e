"""Operators against brute force, with nulls, empty and repeated rows, ties and clashing column names."""

import io
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tests.llm import brute

from levelgraph.llm import decontamination, learning, licences, line_quality, mixing, near_duplicates, pii, quality_rules, text, token_counts, token_file, token_output, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
BASE = " ".join(f"word{k}" for k in range(60))
EDITED = BASE.replace("word30", "other")
ROWS = [
    (1, BASE, "en", "a", 1), (2, BASE, "en", "a", 1), (3, EDITED, "en", None, 1), (4, None, None, None, None), (5, "", "en", "b", 0), (6, " \n\t", "en", "b", 3),
    (7, "one two", "en", "b", 1), (8, "ONE\ttwo", "de", "c", 1), (9, "one two three four five six " * 200, "en", "c", 1), (None, BASE, "en", "a", 1), (10, "é ü ñ " * 30, "es", "a", 1),
    (11, "mail me: joe.b@mail.example.com or +1 (239) 555-1768, ip 10.0.0.255 and 300.1.1.1, card 4539 1488 0343 6467", "en", "a", 1),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def clash(docs):
    """Extra columns with names that operators use themselves."""
    names = ["key", "rank", "score", "kept", "size", "label", "doc", "a", "b", "start", "_copies", "_row", "_slot", "_id", "_key", "_tilt", "slot", "c0", "a.b", "spans", "personal_data", "of_email", "level", "cell", "x`y"]
    return docs.select("*", *[F.lit(n).alias(n) for n in names])


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(k, k % 2, k % 3 == 0 and 1 or 0) for k in range(1, 12)], "doc_id long, quality int, toxic int")


def rows(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


def test_words_and_hashes():
    texts = ["a b", "", None, "b  a\n", "x" * 200_000 + " a", "a\x1cb é"]
    w = text.words(pa.array(texts))
    assert w.counts.tolist() == [len(brute.words(t)) for t in texts]
    h = w.hashes()
    flat = [x for t in texts for x in brute.words(t)]
    assert len({(x, int(y)) for x, y in zip(flat, h)}) == len(set(flat)) == len(set(h.tolist()))


def test_near_duplicates(docs, empty, clash):
    got = rows(near_duplicates.near_duplicate_groups(clash))
    want = brute.near_groups([(i, t) for i, t, *_ in ROWS if i is not None])
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items() if i is not None} == want
    assert got[None]["kept"] and got[None]["component_id"] is None
    assert near_duplicates.near_duplicate_groups(empty).count() == 0
    kept = near_duplicates.drop_near_duplicates(clash)
    assert kept.columns == clash.columns and {r["doc_id"] for r in kept.collect()} == {None, 1, 4, 5, 6, 7, 9, 10, 11}


def test_near_duplicates_of_a_tables_texts(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet").select("doc_id", "text")
    want = brute.near_groups([(r["doc_id"], r["text"]) for r in docs.collect()])
    got = rows(near_duplicates.near_duplicate_groups(docs))
    assert {i: (r["n_shingles"], r["component_id"]) for i, r in got.items()} == want


def test_mix(docs, empty, clash):
    out = mixing.mix(clash).collect()
    assert len(out) == len(ROWS) and mixing.mix(empty).count() == 0
    assert all(r["taken"] <= 2 * r["size"] and r["taken"] == r["copies"] * r["size"] for r in out)
    by = {r["source"]: r for r in out}
    assert sum(r["target"] for r in by.values()) == pytest.approx(1.5 * sum(r["size"] for r in out))
    assert all(r["target"] <= 2 * r["source_size"] + 1e-9 for r in by.values())
    mixed = mixing.mixed_documents(clash)
    assert mixed.columns == clash.columns and mixed.count() == sum(r["copies"] for r in out)
    assert mixing.mixed_documents(empty).count() == 0 and all(r["x`y"] == "x`y" and r["a.b"] == "a.b" for r in mixed.collect())


def test_mix_hits_targets(spark):
    docs = spark.createDataFrame([(i, "w " * (i % 7 + 1), f"s{i % 3}") for i in range(3000)], "doc_id long, text string, source string")
    for r in mixing.mix(docs, share=0.7).groupBy("source").agg(F.sum("taken").alias("t"), F.first("target").alias("g")).collect():
        assert abs(r["t"] - r["g"]) <= 4
    tilted = mixing.mix(docs, share=0.1, importance=F.when(F.col("doc_id") % 2 == 0, 4.0).otherwise(1.0)).groupBy((F.col("doc_id") % 2).alias("odd")).agg(F.sum("copies").alias("n")).collect()
    counts = {r["odd"]: r["n"] for r in tilted}
    assert counts[0] > 2 * counts[1]


def mixed_by_hand(rows, targets, most=2, seed=11, tilt=None):
    """(id, size, source) -> copies, by sorting each source in memory."""
    import hashlib
    import math

    out = {}
    for source, target in targets.items():
        mine = [(i, n, (tilt or (lambda i, n: max(1, int(math.sqrt(n + 1) * 1024))))(i, n)) for i, n, s in rows if s == source]
        level, capped = 0.0, set()
        while target < most * sum(n for _, n, _ in mine):
            level = (target - most * sum(n for i, n, _ in mine if i in capped)) / sum(n * x for i, n, x in mine if i not in capped)
            more = {i for i, n, x in mine if n and level * x >= most}
            if more == capped:
                break
            capped = more
        else:
            level = 1e300
        order, ahead, due = [], 0, target
        for i, n, x in mine:
            e = min(level * x, float(most))
            out[i] = math.floor(e)
            due -= math.floor(e) * n
            if e > math.floor(e):
                u = (int(hashlib.md5(f"{seed}:{i}:{n}".encode()).hexdigest()[:13], 16) + 0.5) / (1 << 52)
                p = min(max(e - math.floor(e), 1e-9), 1 - 1e-9)
                odds = (u / (1 - u)) / (p / (1 - p))
                order.append((odds / (1 + odds), i, n))
        for _, i, n in sorted(order):
            if ahead + n / 2 > due:
                break
            out[i] += 1
            ahead += n
    return out


def test_mix_against_a_sort_in_memory(spark):
    """Capped documents, a hot source cut in small cells, and odds that differ by size."""
    rng = np.random.default_rng(5)
    rows = [(i, int(rng.integers(0, 4)) if i % 3 else int(rng.integers(1, 900)), "hot" if i % 3 else f"s{i % 4}") for i in range(4000)]
    docs = spark.createDataFrame([(i, "w " * n, s) for i, n, s in rows], "doc_id long, text string, source string")
    for share, importance in ((0.4, None), (1.5, None), (1.5, F.when(F.col("doc_id") % 50 == 0, 40.0).otherwise(1.0))):
        got = mixing.mix(docs, share=share, importance=importance, cell_rows=8).collect()
        targets = {r["source"]: r["target"] for r in got}
        tilt = None if importance is None else lambda i, n: 40 * 1024 if i % 50 == 0 else 1024
        assert {r["doc_id"]: r["copies"] for r in got} == mixed_by_hand(rows, targets, tilt=tilt)
        if importance is not None:
            assert {r["copies"] for r in got if r["doc_id"] % 50 == 0 and r["size"] and r["source"] != "hot"} == {2}


def test_mix_of_ties_and_repeated_rows(spark):
    docs = spark.createDataFrame([(1, "a b", "x")] * 500 + [(2, "a b", "x")] * 500 + [(None, "a", None)] * 3, "doc_id long, text string, source string")
    out = mixing.mix(docs, cell_rows=4).collect()
    assert len(out) == 1003 and len({(r["doc_id"], r["copies"]) for r in out}) == 3 and sum(r["taken"] for r in out if r["source"] == "x") in (2000, 3000, 4000)


def test_token_output(docs, empty, clash):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(token_output.default_tokenizer())
    got = sorted((r["start"], r) for r in token_output.token_table(clash).collect())
    ids = [(i, np.array(tok.encode(t or "", add_special_tokens=False).ids + [2], dtype="<u4")) for i, t, *_ in sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0))]
    at = 0
    for (i, x), (start, r) in zip(ids, got, strict=True):
        assert (r["doc_id"], start, r["n_tokens"], r["ids_crc32"]) == (i, at, len(x), zlib.crc32(x.tobytes()))
        at += len(x)
    assert token_output.token_table(empty).count() == 0


@pytest.mark.parametrize("odd", ["a ~ b", "<|endoftext|> x", "Ⅷ ﬁ É", "I'm don't 'S", "a\x1cb", "x,y. z.,", "\xa0a\x85b", "日本 語", "ÀÉ, Ñ.", "a~b ~~ c"])
def test_word_encoder_matches_whole_texts(odd):
    enc = token_output.encoder(token_output.default_tokenizer())
    assert enc.encode(odd) == enc._pack(odd)


def test_shard_random_access():
    sink = io.BytesIO()
    w = token_file.ShardWriter(sink, frame_bytes=64)
    want = {i: np.arange(i, dtype="<u4") for i in range(40)}
    for i, x in want.items():
        w.add(i, x.tobytes())
    w.add(None, b"")
    w.close()
    reader = token_file.ShardReader(io.BytesIO(sink.getvalue()))
    assert all((x == want[i]).all() for i, x in reader.scan() if i is not None) and len(reader.entries) > 5
    assert [(i, x.tolist()) for i, x in reader.scan([7])] == [(7, list(range(7)))]
    import zstandard

    plain = zstandard.ZstdDecompressor().stream_reader(io.BytesIO(sink.getvalue()), read_across_frames=True).read()
    assert plain == b"".join(x.tobytes() for x in want.values())
    broken = bytearray(sink.getvalue())
    broken[20] ^= 0xFF
    with pytest.raises((ValueError, zstandard.ZstdError)):
        list(token_file.ShardReader(io.BytesIO(bytes(broken))).scan())


def test_token_counts(docs, empty):
    vocabulary = token_counts.load_vocabulary(token_counts.default_vocabulary())
    counter = token_counts.TrieCounter(vocabulary)

    def alone(word):
        s = token_counts.MARK + word
        best = [(0.0, 0)]
        for end in range(1, len(s) + 1):
            n = len(s[end - 1].encode())
            options = [(best[end - 1][0] + n * counter.byte, -(best[end - 1][1] + n))]
            options += [(best[b][0] + vocabulary[s[b:end]], -(best[b][1] + 1)) for b in range(end) if s[b:end] in vocabulary]
            score, count = max(options)
            best.append((score, -count))
        return best[-1][1]

    words = {w for _, t, *_ in ROWS for w in brute.words(t)} | {"prefix", "prefixes", "pre", "日本語", "𝔘nicode"}
    counter.insert(words)
    assert all(counter.cache[w] == alone(w) for w in words)
    got = rows(token_counts.count_tokens(docs))
    assert got[4]["n_tokens"] == got[5]["n_tokens"] == 0 and got[7]["n_pretokens"] == 2
    assert token_counts.count_tokens(empty).count() == 0


def test_quality_rules(docs, empty, labels):
    got = {(r["doc_id"], r["n_words"]): r for r in quality_rules.apply_rules(docs).collect()}
    for i, t, *_ in ROWS:
        ws = brute.words(t)
        c = Counter(zip(ws, ws[1:], ws[2:]))
        cover = {k + d for k in range(len(ws) - 2) if c[tuple(ws[k : k + 3])] > 1 for d in range(3)}
        r = got[i, len(ws)]
        assert (r["word_chars"], r["n_repeat_words"]) == (sum(map(len, ws)), len(cover))
        assert r["base_failed"] == (len(ws) < 50 or 100 * len(cover) > 50 * len(ws))
    assert quality_rules.apply_rules(empty).count() == 0
    quality_rules.apply_rules(docs, quality_rules.fit(docs, labels)).collect()
    quality_rules.fit(empty, labels)


def test_character_grams():
    """Slots of the grams are those of plain slices of each blank-padded word."""
    batch = ["ab  cde\tf", None, "", "été ñandú日本語x", " a ", "wxyz" * 3]
    slots, first = quality_rules._grams(text.words(pa.array(batch)))
    seen = {}
    for k, t in enumerate(batch):
        padded = [f" {w} " for w in brute.words(t)]
        grams = [p[i : i + 4] for p in padded for i in range(len(p) - 3)]
        mine = slots[first[k] : first[k + 1]].tolist()
        # a gram that starts in the blank after a word is that blank with the next word
        assert len(mine) == len(grams)
        for g, s in zip(grams, mine, strict=True):
            assert seen.setdefault(g, s) == s
    assert len(set(seen.values())) == len(seen)


def test_held_out_quality_rules(spark, tiny):
    d = tiny.replace("sf0.001", "sf0.1")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{d}/labels.parquet")
    held = learning.fold("doc_id", 5) == 0
    model = quality_rules.fit(docs, labels, allowed=~held)
    scored = quality_rules.apply_rules(docs, model).join(labels, "doc_id").where(held)
    # repetition is the rules' part, so the classifier is judged on rows that pass them
    kept = {(r["quality"], r["base_failed"]): r["p"] for r in scored.groupBy("quality", "base_failed").agg(F.avg(F.col("kept").cast("int")).alias("p")).collect()}
    assert kept[1, False] > 0.97 and kept[0, False] < 0.05 and kept[0, True] == 0


def test_line_quality(docs, empty, labels, clash):
    model = line_quality.fit(docs, labels, steps=5)
    got = rows(line_quality.score_quality(docs, model))
    assert all(0 <= r["score"] <= 1 for r in got.values()) and got[4]["n_lines"] == 0
    assert line_quality.drop_low_quality(clash, model, at=0.0).count() == len(ROWS)
    assert line_quality.fit(empty, labels).score(np.array([0.5]))[0] > 0.5
    assert line_quality.score_quality(empty, model).count() == 0


def test_chain_against_enumeration():
    rng = np.random.default_rng(1)
    unary, stay = rng.normal(size=4), (0.3, 0.7, -0.4)
    total, bad = 0.0, np.zeros(4)
    for k in range(16):
        y = [(k >> i) & 1 for i in range(4)]
        s = sum(u for u, v in zip(unary, y) if v) + sum(stay[2] if a != b else stay[a] for a, b in zip(y, y[1:]))
        total += np.exp(s)
        bad += np.array(y) * np.exp(s)
    got, _ = line_quality.marginals(np.concatenate([unary, unary[:1]]), stay, np.array([0, 4, 4, 5]))
    assert np.allclose(got[:4], bad / total) and np.isclose(got[4], learning.sigmoid(unary[0]))


def test_held_out_quality_and_toxicity(spark, tiny):
    d = tiny.replace("sf0.001", "sf0.1")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    q = line_quality.op7_line_quality(spark, d).join(labels, "doc_id").where("held_out").groupBy("quality").agg(F.avg("predicted").alias("p")).collect()
    q = {r["quality"]: r["p"] for r in q}
    assert q[1] > 0.97 and q[0] < 0.05
    t = toxicity.op5_toxicity(spark, d).join(labels, "doc_id").where("held_out").groupBy("toxic").agg(F.avg("predicted").alias("p")).collect()
    t = {r["toxic"]: r["p"] for r in t}
    assert t[1] > 0.9 and t[0] < 0.01
    assert docs.count()


def test_toxicity(spark, empty, docs, clash, labels):
    """A group's name that goes with the label, as abuse aimed at a group does, must not count by itself."""
    rng = np.random.default_rng(2)
    texts = []
    for k in range(900):
        toxic = k % 3 == 0
        abusive, names = (rng.random() < 0.75, rng.random() < 0.7) if toxic else (False, rng.random() < 0.06)
        words = [f"w{x}" for x in rng.integers(0, 400, 14)] + ["awfulword"] * abusive + ["women"] * names
        texts.append((k, " ".join(rng.permutation(words)) + ".", int(toxic)))
    d = spark.createDataFrame([(k, t) for k, t, _ in texts], "doc_id long, text string")
    marks = spark.createDataFrame([(k, 1, y) for k, _, y in texts], "doc_id long, quality int, toxic int")
    model, free = toxicity.fit(d, marks), toxicity.fit(d, marks, pair_penalty=0.0, mention_weight=0.0)
    plain = [" ".join(f"w{x}" for x in rng.integers(0, 400, 12)) for _ in range(200)]
    neutral = pa.array([f"{t} women" for t in plain])
    gap = lambda m: float(np.abs(m.score(neutral) - m.score(pa.array(plain))).mean())
    wrong = lambda m: float((m.score(neutral) >= 0.5).mean())
    assert gap(model) < 0.5 * gap(free) and wrong(model) < wrong(free) and wrong(model) < 0.05
    penalised = toxicity.fit(d, marks, mention_weight=0.0)
    assert gap(penalised) < gap(free)
    caught = model.score(pa.array([f"{t} awfulword" for t in plain]))
    assert (caught >= 0.5).mean() > 0.9
    assert toxicity.score_toxicity(empty, model).count() == 0 and toxicity.score_toxicity(clash, model).count() == len(ROWS)
    assert {r["doc_id"] for r in toxicity.score_toxicity(docs, model).collect()} == {i for i, *_ in ROWS}
    assert toxicity.fit(empty, labels).score(pa.array(["a", None])).tolist() == toxicity.fit(empty, labels).score(pa.array(["", "b"])).tolist()
    toxicity.fit(docs, labels)


def test_toxicity_does_not_depend_on_layout(spark, tiny):
    d = tiny.replace("sf0.001", "sf0.01")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet").select("doc_id", "text"), spark.read.parquet(f"{d}/labels.parquet")
    a = toxicity.fit(docs, labels)
    b = toxicity.fit(docs.repartition(7, "text"), labels.repartition(3))
    assert np.array_equal(a.features, b.features) and np.array_equal(a.weights, b.weights) and (a.slope, a.shift) == (b.slope, b.shift)


def test_swapped_names():
    assert toxicity.swapped("the Women sang", 0) == [("the Women sang", "the men sang")]
    (a, b), (c, plain) = toxicity.swapped("they sang", 3 + (1 << 8) + (1 << 16))
    assert (a, b, c, plain) == ("they sang refugees", "they sang immigrants", "they sang refugees", "they sang")


def test_licences(spark, empty):
    texts = [(1, "Released under the MIT License."), (2, "x All rights reserved. all  RIGHTS-reserved"), (3, None), (4, ""), (5, "licensed under CC BY-NC 4.0, general public license"), (6, "the license of the mit"), (6, "the license of the mit")]
    d = spark.createDataFrame(texts, "doc_id long, text string").withColumn("row", F.lit(1)).withColumn("words", F.lit("w"))
    got = rows(licences.scan_licences(d))
    assert "mit" in got[1]["labels"].split(",") and got[1]["n_base"] == 0
    assert (got[2]["n_base"], got[2]["first_word"], got[2]["last_word"], got[2]["base_labels"]) == (2, 1, 4, "reserved")
    assert got[3]["n_words"] == 0 and got[3]["labels"] == "" and got[3]["score"] == 0
    assert got[5]["base_labels"] == "cc-by,gpl" and "cc-by-nc" in got[5]["labels"].split(",")
    assert got[6]["labels"] == "" and licences.scan_licences(d).count() == 7 and licences.scan_licences(empty).count() == 0


MIT_PERMISSION = licences.TEMPLATES[2][1]


def test_licences_of_several_notices_and_long_files(spark):
    bsd, mpl = (next(t for label, t, _ in licences.TEMPLATES if label == name) for name in ("bsd", "mpl-2.0"))
    apache, mit, nc = "licensed under the apache license version 2 0", "released under the mit license", "licensed under cc by nc 4 0"
    filler = " x ".join(licences.VOCABULARY)
    texts = [(1, f"{MIT_PERMISSION} {apache}"), (2, f"{bsd} {MIT_PERMISSION} {mpl} {nc}"), (3, f"{bsd} {mpl} {mit}"), (4, f"{filler} y {apache} y {filler}"), (5, filler)]
    got = {i: r["labels"].split(",") for i, r in rows(licences.scan_licences(spark.createDataFrame(texts, "doc_id long, text string"))).items()}
    assert got[1] == ["apache-2.0", "mit"] and got[2] == ["bsd", "cc-by", "cc-by-nc", "mit", "mpl-2.0"]
    assert got[3] == ["bsd", "mit", "mpl-2.0"] and got[4] == ["apache-2.0"] and got[5] == [""]


def test_licences_of_other_versions_and_parts_of_notices(spark):
    gpl = "under the terms of the GNU General Public License as published by the Free Software Foundation; either version {} of the License, or later"
    texts = [
        (1, "under the GNU General Public License version 2 only"), (2, "Apache License, Version 1.1"), (3, gpl.format(2)), (4, gpl.format(3)), (5, "GNU General Public License, version 3"),
        (6, "Apache License, Version 2.0"), (7, "MIT License"), (8, " ".join(MIT_PERMISSION.split()[:9])), (9, "Mozilla Public License, Version 1.1"), (10, "the Creative Commons Attribution-ShareAlike 4.0 International License"),
    ]
    got = {i: r["labels"] for i, r in rows(licences.scan_licences(spark.createDataFrame(texts, "doc_id long, text string"))).items()}
    assert got == {1: "gpl", 2: "", 3: "gpl", 4: "gpl,gpl-3.0", 5: "gpl,gpl-3.0", 6: "apache-2.0", 7: "mit", 8: "", 9: "", 10: ""}


def test_licences_of_further_kinds(spark):
    texts = [
        (1, "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"), (2, "This is free and unencumbered software released into the public domain."),
        (3, "Distributed under the Boost Software License, Version 1.0."), (4, "under the GNU Affero General Public License, version 3"), (5, "GNU Affero General Public License"),
        (6, "Eclipse Public License v2.0"), (7, "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages"),
        (8, "the software is public and free of warranty, and the license is provided"),
    ]
    got = {i: r["labels"] for i, r in rows(licences.scan_licences(spark.createDataFrame(texts, "doc_id long, text string"))).items()}
    assert got == {1: "isc", 2: "unlicense", 3: "bsl-1.0", 4: "agpl-3.0,gpl", 5: "gpl", 6: "epl-2.0", 7: "zlib", 8: ""}


def test_personal_data(docs, empty, spark, clash):
    found = {r["doc_id"]: [(s["kind"], s["start"], s["end"]) for s in r["personal_data"]] for r in pii.find_personal_data(docs).collect()}
    t = ROWS[-1][1]
    want = [(k, t.index(x), t.index(x) + len(x)) for k, x in (("email", "joe.b@mail.example.com"), ("phone", "+1 (239) 555-1768"), ("ip", "10.0.0.255"), ("card", "4539 1488 0343 6467"))]
    assert found[11] == want and found[4] == found[5] == []
    tricky = spark.createDataFrame([(1, "a@b.c.x_y@d.e é@x.y 😀 iban DE89 3704 0044 0532 0130 00 to bank, 1.2.3.4.5.6.7.8"), (2, "9" * 30_000 + " a@" + "b." * 20_000)], "doc_id long, text string")
    got = {r["doc_id"]: [(s["kind"], r["text"][s["start"] : s["end"]]) for s in r["personal_data"]] for r in pii.find_personal_data(tricky).collect()}
    assert ("email", "a@b.c.x") in got[1] and ("email", "_y@d.e") in got[1] and ("iban", "DE89 3704 0044 0532 0130 00") in got[1] and ("ip", "5.6.7.8") in got[1]
    assert pii.find_personal_data(empty).count() == 0
    assert "joe.b@" not in rows(pii.redact(docs))[11]["text"]
    hidden = pii.redact(clash)
    assert hidden.columns == clash.columns and all(r["personal_data"] == "personal_data" for r in hidden.collect())
    named = pii.find_personal_data(clash)
    assert named.columns == [*(c for c in clash.columns if c != "personal_data"), "personal_data"] and {r["spans"] for r in named.collect()} == {"spans"}


def test_ibans_before_capitals_numbers_and_stops(spark):
    plain, spaced, british = "DE89370400440532013000", "DE89 3704 0044 0532 0130 00", "GB82 WEST 1234 5698 7654 32"
    cases = [
        (f"IBAN {plain} Please", [plain]), (f"{spaced} Bitte", [spaced]), (f"iban {spaced} 00 EUR", [spaced]), (f"{spaced}.", [spaced]), (f"iban {plain} IBAN", [plain]), (spaced, [spaced]),
        (f"{spaced} {british} A", [spaced, british]), (f"XY12 {plain} 7", [plain]), (f"\U0001f600 {british}, {plain}\n", [british, plain]), (f"{plain}x", []), ("DE89370400440532013001 Please", []), ("DE89 3704", []), (None, []),
        ("MT84 MALT 0110 0001 2345 MTLC AST0 01S Z", ["MT84 MALT 0110 0001 2345 MTLC AST0 01S"]), ("XX57 1234 5678 9012 345 Now", ["XX57 1234 5678 9012 345"]),
    ]
    d = spark.createDataFrame([(k, t) for k, (t, _) in enumerate(cases)], "doc_id long, text string")
    got = {r["doc_id"]: [r["text"][s["start"] : s["end"]] for s in r["personal_data"] if s["kind"] == "iban"] for r in pii.find_personal_data(d).collect()}
    assert got == {k: want for k, (_, want) in enumerate(cases)}


def test_decontamination(spark, empty):
    item = "which of these small rivers runs north through the old town before it meets the sea near the harbour wall"
    words = item.split()
    edited = " ".join("zzz" if k % 6 == 5 else w for k, w in enumerate(words))
    d = spark.createDataFrame([(1, "intro " + item + " end"), (2, "x y " + edited), (3, "the old town is far from the sea"), (4, None), (5, ""), (6, item.upper()), (6, item)], "doc_id long, text string").withColumn("score", F.lit(1))
    bench = spark.createDataFrame([(10, item), (11, None), (12, ""), (13, "two words")], "item_id long, text string")
    hits = decontamination.find_leaks(d, bench).collect()
    assert sorted((r["doc_id"], r["item_id"]) for r in hits) == [(1, 10), (2, 10), (6, 10), (6, 10)]
    assert next(r for r in hits if r["doc_id"] == 1)["first_word"] == 1
    several = decontamination.find_leaks(d, bench, pass_bytes=40).collect()
    assert sorted(map(tuple, several)) == sorted(map(tuple, hits))
    assert sorted(r["doc_id"] for r in decontamination.drop_contaminated(d, bench).collect()) == [3, 4, 5]
    assert decontamination.find_leaks(empty, bench).count() == 0 and decontamination.find_leaks(d, bench.limit(0)).count() == 0


def test_decontamination_reaches_every_alignment(spark):
    rng = np.random.default_rng(3)
    template = [f"t{k}" for k in range(35)]
    other = lambda word, at=17: " ".join([*template[:at], word, *template[at + 1 :]])
    bench = [(k, other(f"own{k}")) for k in range(10)] + [(10, " ".join(f"a{k}" for k in range(20))), (11, " ".join(f"b{k % 7}" for k in range(15)))]
    texts = ["x y " + other("else"), " ".join(template[9:]), " ".join(template[:8]), " ".join("zz" if k % 4 == 3 else f"a{k}" for k in range(20)), " ".join(f"a{k} q{k}" for k in range(20))]
    for _ in range(120):
        words = bench[int(rng.integers(12))][1].split()
        rate = rng.uniform(0.1, 0.7)
        edited = [x for w in words for x in (([], ["n"], [w, "n"], [w, "n", "m"])[rng.integers(4)] if rng.random() < rate else [w])]
        texts.append(" ".join([*(["f"] * int(rng.integers(30))), *edited, *words[: int(rng.integers(5))]]))
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["score"] for r in decontamination.find_leaks(d, spark.createDataFrame(bench, "item_id long, text string")).collect()}
    ids = {}
    code = lambda t: np.array([ids.setdefault(w, len(ids)) for w in t.split()])
    want = {(k, i): decontamination.align(code(t), code(x))[0] / (2 * len(t.split())) for k, x in enumerate(texts) for i, t in bench}
    assert got == {k: v for k, v in want.items() if v >= 0.5}
    assert all((k, i) in got for k in (0, 1) for i in range(10)) and (3, 10) in got and (4, 10) in got


def test_decontamination_of_short_items_and_scripts_without_blanks(spark):
    han = "春眠不覚暁処処聞啼鳥夜来風雨声花落知多少"
    bench = spark.createDataFrame([(1, "Zanzibar"), (2, "two words"), (3, "these three words"), (4, han), (5, "?!")], "item_id long, text string")
    texts = ["in zanzibar today", "two, words", "two other words", "say these three words now", "these three", "前文" + han[:12] + "他" + han[13:] + "abc", "春眠", "zanzibar" + han, "", None]
    hits = decontamination.find_leaks(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), bench).collect()
    got = {(r["doc_id"], r["item_id"]): (r["first_word"], r["last_word"]) for r in hits}
    assert got == {(0, 1): (1, 1), (1, 2): (0, 1), (3, 3): (1, 3), (5, 4): (2, 21), (7, 1): (0, 0), (7, 4): (1, 20)}
