"""Operators against brute force, libraries, exact round trips and held-out accuracy."""

import hashlib
import random
import re
import struct

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from momenttree.llm import bpe, components, decontaminate, labelled, licences, minhash, quality, secrets, simhash, token_counts, toxicity

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def documents(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def texts(documents):
    return {r.doc_id: r.text or "" for r in documents.select("doc_id", "text").collect()}


def test_bpe_matches_the_library(spark, documents, texts):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(bpe.default_vocabulary())
    got = {r.doc_id: r for r in bpe.digests(documents).collect()}
    for key, text in texts.items():
        ids = library.encode(text, add_special_tokens=False).ids
        assert got[key].n_tokens == len(ids)
        assert got[key].ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert got[key].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    encoded = bpe.encode(documents)
    assert {r.doc_id: r.decoded for r in bpe.decode(encoded).collect()} == texts


@pytest.mark.parametrize("text", ["", " ", "<|endoftext|>", "a<|endoftext|> b<|endoftext|><|endoftext|>", "ᠠ ԰՘ x₏1 ⅷ", "\x00\x1c a\x85 b　", "x" * 4000 + "  \n\n y", "😀👩‍👧 naïve", "aaaaaaaaaaaaaaab"])
def test_bpe_on_odd_texts(text):
    from tokenizers import Tokenizer

    library, own = Tokenizer.from_file(bpe.default_vocabulary()), bpe.load(bpe.default_vocabulary())
    ids = library.encode(text, add_special_tokens=False).ids
    assert own.encode(text) == ids
    assert own.decode(ids) == library.decode(ids, skip_special_tokens=False)


def test_decoding_broken_sequences():
    own = bpe.load(bpe.default_vocabulary())
    assert own.decode([own.of_byte[0xE2], own.of_byte[0x41]]) == b"\xe2A".decode("utf-8", "replace")


def brute_sections(text, spans, sections, rule):
    counts = [0.0] * len(sections)
    for a, b in spans:
        shares = [max(0, min(e, b) - max(s, a)) for s, e in sections]
        if rule == "share":
            for k, x in enumerate(shares):
                counts[k] += x / (b - a)
        elif rule == "most":
            if max(shares):
                counts[shares.index(max(shares))] += 1
        else:
            at = a if rule == "start" else b - 1
            for k, (s, e) in enumerate(sections):
                counts[k] += s <= at < e
    return counts


@pytest.mark.parametrize("rule", token_counts.RULES)
def test_token_attribution(spark, rule):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(bpe.default_vocabulary())
    text = "Tokenisation crosses boundaries, naïvely 😀 so.\n\n  Next line of it\nlast"
    sections = [(0, 3), (3, 9), (12, 14), (14, 45), (45, 60)]
    docs = spark.createDataFrame([(1, text, sections)], "doc_id bigint, text string, s array<struct<first:int,end:int>>")
    got = [r.n_tokens for r in token_counts.count(docs, rule=rule, sections_col="s").orderBy("section").collect()]
    own = bpe.load(bpe.default_vocabulary())
    raw, at, spans = text.encode(), 0, []
    for i in library.encode(text, add_special_tokens=False).ids:
        n = len(own.bytes_of[i])
        start = len(raw[:at].decode("utf-8", "ignore"))
        spans.append((start, len(raw[: at + n].decode("utf-8", "ignore")) + (1 if raw[: at + n].decode("utf-8", "replace").endswith("�") else 0)))
        at += n
    assert np.allclose(got, brute_sections(text, spans, sections, rule))


def test_line_sections_add_up(spark, documents):
    rows = token_counts.count(documents).groupBy("doc_id").agg(F.sum("n_tokens").alias("a"), F.max("doc_tokens").alias("b")).collect()
    assert all(r.a == r.b for r in rows)


def test_segments_are_maximal():
    """Against the definition: recursively the best segment, then what is left and right of it."""

    def brute(seq, base=0):
        best = None
        for i in range(len(seq)):
            for j in range(i, len(seq)):
                s = sum(seq[i : j + 1])
                if s > 1e-12 and (best is None or s > best[0] + 1e-12 or (abs(s - best[0]) < 1e-12 and j - i < best[2] - best[1])):
                    best = s, i, j
        if best is None:
            return []
        s, i, j = best
        return [*brute(seq[:i], base), (round(s, 6), i + base, j + base), *brute(seq[j + 1 :], base + j + 1)]

    r = random.Random(1)
    for _ in range(300):
        seq = [r.choice([-0.37, -0.37, -0.37, r.random() * 2]) for _ in range(r.randrange(1, 14))]
        got = toxicity.segments([(k, x) for k, x in enumerate(seq) if x > 0], 0.37)
        assert sorted((round(s, 6), a, b) for s, a, b in got) == sorted(brute(seq)), seq


def auc(rows):
    rows = sorted(rows)
    ranks = {}
    for k, (s, _) in enumerate(rows):
        ranks.setdefault(s, []).append(k + 1)
    mean = {s: np.mean(v) for s, v in ranks.items()}
    pos = [mean[s] for s, y in rows if y]
    n1, n0 = len(pos), len(rows) - len(pos)
    return (sum(pos) - n1 * (n1 + 1) / 2) / (n1 * n0)


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    good = quality.judge(docs, labels).where("held_out").join(labels, "doc_id").select("score", "quality").collect()
    assert auc([tuple(r) for r in good]) > 0.97
    bad = toxicity.judge(docs, labels).where("held_out").join(labels, "doc_id").select("score", "toxic").collect()
    assert auc([tuple(r) for r in bad]) > 0.9
    found = [r.score >= 0.5 for r in bad if r.toxic]
    assert np.mean(found) >= 0.9 and np.mean([r.score >= 0.5 for r in bad if not r.toxic]) < 0.01
    seen = [r.score >= quality.THRESHOLD for r in good if r.quality]
    assert np.mean(seen) >= 0.98 and np.mean([r.score >= quality.THRESHOLD for r in good if not r.quality]) < 0.05


def test_toxicity_score_by_definition():
    """Segments by recursion, expected counts and tails of sums by their formulas, against the model's scores."""
    import math

    def best_segments(seq):
        sums = [(sum(seq[i : j + 1]), -(j - i), i, j) for i in range(len(seq)) for j in range(i, len(seq))]
        s, _, i, j = max(sums, default=(0, 0, 0, 0))
        return [*best_segments(seq[:i]), s, *best_segments(seq[j + 1 :])] if s > 1e-12 else []

    model = toxicity.ToxicModel({"bad$": 3.1, "ugly$": 2.3, "slim": 1.7}, rate=1.3, spread=0.02, bias=-4.0, slopes=(1.5, 2.5), trained=True)
    value = {"bad": 3.1, "ugly": 2.3, "slimy": 1.7, "slimmer": 1.7}
    r = random.Random(5)
    for _ in range(200):
        words = [r.choice(["bad", "ugly", "slimy", "slimmer", "plain", "word", "other", "calm"]) for _ in range(r.randrange(0, 14))]
        words = [w for k in words for w in [k, *["filler"] * r.randrange(0, 9)]]
        found = best_segments([value.get(w, 0.0) - toxicity.PENALTY for w in words])
        log_kn = math.log(0.02 * max(len(words), 1))
        best = max([0.0, *(1.3 * s - log_kn for s in found)]) if found else 0.0
        tails = [0.0]
        for k in range(1, len(found) + 1):
            t = 1.3 * sum(sorted(found)[-k:]) - k * log_kn
            if t > k:
                tails.append(-math.log(math.exp(-t) * t ** (k - 1) / (math.factorial(k) * math.factorial(k - 1))))
        want = 1 / (1 + math.exp(-(-4.0 + 1.5 * best / 10 + 2.5 * math.log1p(max(tails)))))
        assert math.isclose(model.score(" ".join(words)), want, rel_tol=1e-9)
    assert model.score("") == 1 / (1 + math.exp(4.0))


def test_quality_scores_by_all_pairs(spark, documents):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    model = quality.train(documents, labels)
    got = {r.doc_id: r.score for r in quality.judge(documents, labels).collect()}
    for r in documents.orderBy("doc_id").limit(25).collect():
        index, value = quality.features(r.text or "", r.n_chars)
        scaled = model.v[index] * np.asarray(value)[:, None]
        pairs = np.triu(scaled @ scaled.T, 1).sum()
        assert np.isclose(got[r.doc_id], 1 / (1 + np.exp(-(model.b + model.w[index] @ value + pairs))), atol=1e-6)


def test_fingerprints_by_definition(texts):
    from zlib import crc32

    for text in [*list(texts.values())[:12], "", "one", "One two  three", "a b c d e f"]:
        words = [w for w in re.split(rb"[\x00-\x20]+", text.lower().encode()) if w]
        runs = [words[k : k + 5] for k in range(max(len(words) - 4, 1))] if words else []
        hashes = []
        for run in runs:
            x = sum((crc32(w) + 0x9E3779B9) * int(m) for w, m in zip(run, minhash._MIX, strict=False)) % (1 << 64)
            x = (x ^ (x >> 29)) * 0xBF58476D1CE4E5B9 % (1 << 64)
            hashes.append(x >> 32)
        least = [min([(int(a) * h + int(b)) % (1 << 32) for h in hashes], default=0xFFFFFFFF) for a, b in zip(minhash.MULTIPLIERS, minhash.OFFSETS, strict=True)]
        assert minhash.fingerprint_of(text) == bytes((x * 0x9E3779B1 % (1 << 32)) >> 24 for x in least).hex()


def test_folds_are_those_of_crc32(spark):
    import zlib

    rows = spark.range(50).select(F.col("id").alias("doc_id")).select("doc_id", labelled.fold(5).alias("f")).collect()
    assert all(r.f == zlib.crc32(str(r.doc_id).encode()) % 5 for r in rows)


def test_sum_of_squares_identity():
    random_ = np.random.default_rng(0)
    machine = quality.FactorMachine(0.3, random_.normal(size=quality.WIDTH), random_.normal(size=(quality.WIDTH, 3)))
    index, value = np.array([3, 17, 99, 1200]), np.array([0.5, -1.0, 2.0, 0.25])
    pairs = sum(machine.v[index[i]] @ machine.v[index[j]] * value[i] * value[j] for i in range(4) for j in range(i + 1, 4))
    assert np.isclose(machine.logit(index, value), 0.3 + machine.w[index] @ value + pairs)


def brute_fingerprint(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text))
    if not words:
        return 0
    shingles = [" ".join(words[k : k + 3]) for k in range(len(words) - 2)] or [" ".join(words)]
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(x >> b & 1 for x in h) * 2 > len(h))


def brute_classes(prints):
    parent = {d: d for d in prints}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(prints)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if bin(prints[a] ^ prints[b]).count("1") <= 3:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: find(d) for d in ids}


def test_simhash_classes(spark, documents, texts):
    got = {r.doc_id: r for r in simhash.classes(documents).collect()}
    prints = {d: brute_fingerprint(t) for d, t in texts.items()}
    assert {d: r.fp & (1 << 64) - 1 for d, r in got.items()} == prints
    assert {d: r.component_id for d, r in got.items()} == brute_classes(prints)


@pytest.mark.parametrize("paired", [256, 2])
def test_ball_hashing_finds_every_link(spark, paired):
    """Chains and clouds of near fingerprints; with a small bound the ball of radius two takes over."""
    r = random.Random(2)
    prints = set()
    for _ in range(25):
        centre = r.getrandbits(64)
        for _ in range(8):
            x = centre
            for b in r.sample(range(64), r.randrange(0, 4)):
                x ^= 1 << b
            prints.add(x)
    low = r.getrandbits(32)
    prints |= {low | r.getrandbits(32) << 32 for _ in range(12)}  # one half in common
    signed = [x - (1 << 64) if x >> 63 else x for x in prints]
    links = simhash.near_links(spark.createDataFrame([(x,) for x in signed], "fp bigint"), paired)
    got = {x: x for x in signed} | {r.id: r.component for r in components.components(links).collect()}
    want = brute_classes({x: x & (1 << 64) - 1 for x in signed})
    group = lambda m: sorted(sorted(k for k in m if m[k] == c) for c in set(m.values()))
    assert group(got) == group(want)


def test_components_of_chains_stars_and_loops(spark):
    links = [(k, k + 1) for k in range(60)] + [(100, 101 + k) for k in range(40)] + [(300, 300), (400, 401), (401, 400), (None, 5)]
    got = {r.id: r.component for r in components.components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
    assert got == {k: 0 for k in range(61)} | {100 + k: 100 for k in range(41)} | {300: 300, 400: 400, 401: 400}


def brute_spans(text):
    assign = re.compile(r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.A)
    spans = [(m.start(), 0, m.end()) for m in assign.finditer(text) if len(m[1]) >= 6]
    spans += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", text) if len(m[0]) >= 20]
    spans += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", text) if len(m[0]) >= 24]
    return [f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in sorted(spans)]


SECRETS = [
    (1, 'x😀 PassWord = "abcdef" token:short token=abc api_key=\'ZZZZZZ99\' AKIA' + "A" * 16 + " " + "0f" * 12, "a"),
    (2, "no secret here", "b"),
    (3, "AKIA" + "B" * 30 + "\npasswd:  aaaaaa=bbbb passwordtoken=12345678", "c"),
    (4, "wide QmFzZTY0LXRva2Vu1234xyz and only here", "d"),
    (5, "wide copied1example2token3 here", "a"),
    (6, "wide copied1example2token3 here", "b"),
    (7, "wide copied1example2token3 here", "c"),
    (8, "token=copied1example2token3", "d"),
]


def test_secret_spans(spark, documents, texts):
    docs = spark.createDataFrame(SECRETS, "doc_id bigint, text string, source string")
    got = {r.doc_id: r for r in secrets.report(docs).collect()}
    for key, text, _ in SECRETS:
        base = brute_spans(text)
        assert got[key].base_sha256 == hashlib.sha256(",".join(base).encode()).hexdigest(), key
        assert (got[key].n_assign, got[key].n_access, got[key].n_hex) == tuple(sum(s.startswith(k) for s in base) for k in ("assign", "access", "hex"))
        assert set(base) <= set(got[key].spans.split(",")) or not base
    assert got[4].spans == "opaque:5:28" and got[4].n_added == 1
    assert got[5].spans == "" and got[5].n_live == 0  # a widely copied example
    assert got[8].n_live == 0 and got[8].spans.startswith("assign:0:")
    real = {r.doc_id: r for r in secrets.report(documents).collect()}
    assert all(real[d].base_sha256 == hashlib.sha256(",".join(brute_spans(t)).encode()).hexdigest() for d, t in texts.items())
    masked = {r.doc_id: r.text for r in secrets.redact(docs).collect()}
    assert masked[4] == "wide [secret] and only here" and masked[5] == SECRETS[4][1] and masked[8] == SECRETS[7][1]
    assert masked[1] == "x😀 [secret]\" token:short token=abc [secret]' [secret] [secret]"


def test_licences_are_inherited(spark):
    rows = [
        (1, "Released under the MIT License.", "repo/LICENSE"),
        (2, "int main() {}", "repo/src/deep/a.c"),
        (3, "This work is licensed under the GNU General Public License, version 3.", "repo/src/gpl/COPYING"),
        (4, "code", "repo/src/gpl/b.c"),
        (5, "header: Licensed under the Apache License, Version 2.0.\n" + "code " * 50, "repo/src/gpl/c.c"),
        (6, "nothing", "other/x.c"),
        (7, "A licence plate and copyright chatter without a notice", "repo/y.txt"),
    ]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, where string")
    got = {r.doc_id: (r.license, r.found, r.inherited_from) for r in licences.scan(docs, F.col("where")).collect()}
    assert got == {1: ("MIT", "file", None), 2: ("MIT", "inherited", "repo"), 3: ("GPL-3.0", "file", None), 4: ("GPL-3.0", "inherited", "repo/src/gpl"), 5: ("Apache-2.0", "header", None), 6: (None, "none", None), 7: ("MIT", "inherited", "repo")}


LICENCES = [
    ("SPDX-License-Identifier: MIT", "MIT"),
    ("/* SPDX-License-Identifier: Apache-2.0 */\nint main();", "Apache-2.0"),
    (licences._MIT, "MIT"),
    (licences._APACHE, "Apache-2.0"),
    ("GNU GENERAL PUBLIC LICENSE\n   Version 3, 29 June 2007\n\n Everyone may copy it.", "GPL-3.0"),
    ("GNU GENERAL PUBLIC LICENSE\nVersion 3", "GPL-3.0"),
    ("# This program is free software: you can redistribute it and/or modify\n# it under the terms of the GNU General Public License as published by\n# the Free Software Foundation, either version 3 of the License, or\n# (at your option) any later version.", "GPL-3.0"),
    ("Redistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions\nare met:\n1. Redistributions of source code must retain the above copyright\nnotice, this list of conditions and the following disclaimer.", "BSD-2-Clause"),
    ("ISC License", "ISC"),
    ("MIT License\n\nCopyright (c) 2020 A B\n\n" + licences._MIT + "\n\n" + licences._MIT_NOTICE + "\n\n" + licences._WARRANTY, "MIT"),
    ("SPDX-License-Identifier: XYZ-9.9", None),
    ("Copyright 2020 A B. All rights reserved.", None),
    ("copyright and licence chatter on the public domain, without any notice", None),
    ("", None),
    (None, None),
]


def test_everyday_notices(spark):
    docs = spark.createDataFrame([(k, t) for k, (t, _) in enumerate(LICENCES)] * 2, "doc_id bigint, text string")
    rows = [tuple(r) for r in licences.scan(docs, F.concat(F.lit("d"), F.col("doc_id"), F.lit("/x"))).collect()]
    assert {r[0]: r[2] for r in rows} == {k: want for k, (_, want) in enumerate(LICENCES)}
    assert len(rows) == 2 * len(LICENCES) and len(set(rows)) == len(LICENCES)  # repeated rows get equal results


def test_share_counts_repeated_lines(spark):
    docs = spark.createDataFrame([(1, "a\n" * 50 + "Released under the MIT License.\n" * 60), (2, "a\n" * 50 + "Released under the MIT License.\n")], "doc_id bigint, text string")
    assert {r.doc_id: r.found for r in licences.scan(docs, F.concat(F.lit("d/"), F.col("doc_id"))).collect()} == {1: "file", 2: "header"}


def test_secrets_of_a_text_full_of_tokens(spark):
    """Linear in the matches: a text of 0.6 MB with 32,000 tokens, in every kind, masked whole."""
    import time

    r = random.Random(3)
    value = lambda n: "".join(r.choice("abcdef0123456789") for _ in range(n))
    parts = [f"k{k} token={value(8)}" if k % 2 else value(30) for k in range(32_000)]
    text = "é " + "\n".join(parts)
    docs = spark.createDataFrame([(1, text, "a"), (2, "é" * 5_000 + " token=abcdefgh1 " + "😀" * 5_000, "b"), (3, None, "c")], "doc_id bigint, text string, source string")
    began = time.time()
    got = {x.doc_id: x for x in secrets.report(docs).collect()}
    masked = {x.doc_id: x.text for x in secrets.redact(docs).collect()}
    assert time.time() - began < 60
    base = brute_spans(text)
    assert got[1].base_sha256 == hashlib.sha256(",".join(base).encode()).hexdigest()
    assert masked[1] == "é " + "\n".join(f"k{k} [secret]" if k % 2 else "[secret]" for k in range(32_000))
    assert masked[2] == "é" * 5_000 + " [secret] " + "😀" * 5_000 and masked[3] is None


def test_ownership_counts_owners_and_repositories(spark):
    one = [(k, "copy1here2wide3token", "a", f"l{k}") for k in range(8)]  # one owner, many repositories: live
    two = [(10 + k, "both1here2wide3token", "ab"[k % 2], f"l{k}") for k in range(6)]  # two owners, six repositories: copied
    pair = [(20 + k, "pair1here2wide3token", "ab"[k], "l") for k in range(2)]  # two owners, two repositories: live
    docs = spark.createDataFrame(one + two + pair, "doc_id bigint, text string, source string, lang string")
    live = {r.doc_id: r.n_live for r in secrets.report(docs).collect()}
    assert live == {k: 1 for k in range(8)} | {10 + k: 0 for k in range(6)} | {20: 1, 21: 1}


def test_the_sql_twins_on_odd_texts(spark, tmp_path):
    import duckdb

    from momenttree.llm import oracles

    texts = [t for t, _ in LICENCES] + [t for _, t, _ in SECRETS] + ["token=abc token: abcdefgh AKIA" + "B" * 15 + " " + "a" * 23 + " " + "a1" * 12, "x" * 40 + "1 -a1-b2-c3-d4-e5-f6-"]
    docs = spark.createDataFrame([(k, t, "en", f"s{k % 3}", 0) for k, t in enumerate(texts)], "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.toPandas().to_parquet(f"{tmp_path}/documents.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents.parquet'")
    plain = lambda rows: {r[0]: tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows}
    for run, sql in ((licences.scan, oracles.licence_scan()), (secrets.report, oracles.secret_scan())):
        assert plain(run(docs).collect()) == plain(con.execute(sql).fetchall())


def edit_distance(item, text):
    row = list(range(len(item) + 1))
    best = row[-1]
    for c in text:
        new = [0]
        for i, x in enumerate(item, 1):
            new.append(min(row[i] + 1, new[i - 1] + 1, row[i - 1] + (x != c)))
        row = new
        best = min(best, row[-1])
    return best


def test_edit_distance_is_exact():
    r = random.Random(4)
    for _ in range(200):
        a, b = ("".join(r.choice("abc ") for _ in range(r.randrange(1, n))) for n in (90, 140))
        assert decontaminate.edit_distance_within(a, b)[0] == edit_distance(a, b)


def test_decontamination_recall(spark):
    """Items with up to a tenth of their words changed, at any place of a longer text: found or within the target recall."""
    items = [(r.item_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.1/benchmark.parquet").collect()]
    index = decontaminate.ItemIndex.build(items)
    r = random.Random(5)
    for rate, least in ((0.0, 1.0), (0.05, 0.98), (0.1, 0.93)):
        texts, want = [], []
        for _ in range(200):
            k = r.randrange(len(items))
            words = [w.decode() for w in decontaminate.words_of(items[k][1])]
            new = []
            for w in words:
                u = r.random()
                new += [] if u < rate / 3 else ["zz"] if u < 2 * rate / 3 else [w, "qq"] if u < rate else [w]
            if edit_distance(" ".join(words), " ".join(new)) > 0.2 * len(" ".join(words)):
                continue
            texts.append(" ".join(["filler"] * r.randrange(40) + new + ["more", "words"]))
            want.append(items[k][0])
        found = index.matches(texts, 0.8)
        assert np.mean([any(index.ids[i] == w for i in f) for f, w in zip(found, want, strict=True)]) >= least
    assert not any(index.matches(["other words that no item holds " * 20, ""], 0.8))


def test_clean_documents_stay(spark, documents, texts):
    items = spark.read.parquet(f"{SF}/benchmark.parquet")
    index = [b" ".join(decontaminate.words_of(r.text)) for r in items.collect()]
    holds = {d for d, t in texts.items() if any(b" " + x + b" " in b" " + b" ".join(decontaminate.words_of(t)) + b" " for x in index)}
    assert {r.doc_id for r in decontaminate.leaks(documents, items).collect()} >= holds
    assert {r.doc_id for r in decontaminate.drop_leaks(documents, items).collect()} == set(texts) - {r.doc_id for r in decontaminate.leaks(documents, items).collect()}


@pytest.mark.parametrize("partitions", [1, 7])
def test_edited_texts(spark, documents, texts, partitions):
    got = {r.doc_id: r for r in minhash.with_edited(documents, partitions).collect()}
    ids = sorted(texts)
    assert sorted(got) == ids
    for k, d in enumerate(ids):
        text, after = texts[d], texts[ids[(k + 1) % len(ids)]]
        half = len(text) // 2
        new = text[: len(text) - half] + after[:half]
        assert (got[d].n_chars, got[d].edited_sha256) == (len(text), hashlib.sha256(new.encode()).hexdigest())
        assert got[d].fingerprint == minhash.fingerprint_of(text) and got[d].edited_fingerprint == minhash.fingerprint_of(new)
        assert got[d].near_next == minhash.likeness(minhash.fingerprint_of(text), minhash.fingerprint_of(after))


def test_minhash_estimates_jaccard():
    r = random.Random(6)
    errors = []
    for _ in range(60):
        a = [f"w{r.randrange(500)}" for _ in range(300)]
        b = a[: r.randrange(20, 300)] + [f"v{r.randrange(500)}" for _ in range(r.randrange(200))]
        x, y = (set(zip(*(t[k:] for k in range(5)), strict=False)) for t in (a, b))
        errors.append(minhash.likeness(minhash.fingerprint_of(" ".join(a)), minhash.fingerprint_of(" ".join(b))) - len(x & y) / len(x | y))
    assert abs(np.mean(errors)) < 0.02 and np.abs(errors).max() < 0.2


@pytest.mark.parametrize("paired", [64, 1])
def test_near_classes_verify(spark, paired):
    """With a small bound rare shingles choose the pairs."""
    r = random.Random(7)
    rows, doc = [], 0
    for _ in range(12):
        base = [f"w{r.randrange(3000)}" for _ in range(200)]
        for k in range(4):
            new = list(base)
            for _ in range(3 * k):
                new[r.randrange(200)] = f"x{r.randrange(3000)}"
            rows.append((doc, " ".join(new)))
            doc += 1
    shared = " ".join(f"c{k}" for k in range(60))
    rows += [(doc + 3 + k, " ".join(f"u{k}x{j}" for j in range(100)) + " " + shared) for k in range(12)]  # a passage of all, no copies
    rows += [(doc, rows[0][1]), (doc + 1, ""), (doc + 2, "")]
    got = {x.doc_id: x.component_id for x in minhash.near_classes(spark.createDataFrame(rows, "doc_id bigint, text string"), paired=paired).collect()}
    sets = {d: set(minhash.shingles(t).tolist()) for d, t in rows}
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            if a < b and (len(sets[a] & sets[b]) / len(sets[a] | sets[b]) if sets[a] | sets[b] else 1.0) >= 0.8:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    assert got == {d: find(d) for d in sets}
