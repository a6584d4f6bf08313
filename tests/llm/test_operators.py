"""Operators against brute force on small fixtures that hold nulls, empty and long texts, ties, repeated rows and clashing columns."""

import math
import os
import random
import struct
import textwrap
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import xxhash
from pyspark.sql import functions as F

from seqlex.llm import bagminhash, common, ctw, iforest, langid, licences, line_dedup, mixing, resharding, shingles, topk_search, unigram_pieces
from seqlex.llm.common import split_by

WORDS = "alpha beta gamma delta épsilon zeta eta theta iota kappa lambda my ny xi omikron pi rho sigma tau upsilon".split()
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, node string, weight double, h1 string"


def prose(rng, n):
    return " ".join(rng.choice(WORDS) + str(rng.randrange(30)) for _ in range(n))


def rows():
    rng = random.Random(3)
    base = prose(rng, 80)
    near = base.split()
    near[40] = "changed"
    texts = [None, "", " \n\t ", "123 456", base, base, " ".join(near), prose(rng, 3), prose(rng, 4000), "a\n" * 50, "Same line that stands on many sites.\n" + prose(rng, 60)]
    texts += ["Same line that stands on many sites.\n" + prose(rng, 60) for _ in range(12)] + ["▁ 梦😀\x00\r\n  x"]
    out = [(i, t, ["en", "de", None][i % 3], f"s{i % 14}", None, "x", 1.0, "y") for i, t in enumerate(texts)]
    return [*out, out[4], (None, "no id here", None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def words_of(text):
    return [w.lower() if w.isascii() else "".join(c.lower() if c.isascii() else c for c in w) for w in (text or "").replace("\x1c", "_").split()]


def brute_classes(data):
    texts = sorted({t for _, t, *_ in data if t is not None})
    bags = {t: Counter(tuple(w[k : k + 5]) for w in [words_of(t)] for k in range(max(min(1, len(w)), len(w) - 4))) for t in texts}
    parent = {t: t for t in texts}

    def root(t):
        while parent[t] != t:
            t = parent[t]
        return t

    for i, a in enumerate(texts):
        for b in texts[i + 1 :]:
            union = sum((bags[a] | bags[b]).values())
            if union and sum((bags[a] & bags[b]).values()) >= 0.8 * union:
                parent[root(a)] = root(b)
    found = {}
    for i, t, *_ in data:
        if t is not None:
            found.setdefault(root(t), []).append(i)
    return sorted((sorted(x, key=str) for x in found.values()), key=str)


def test_near_duplicate_classes_match_all_pairs(spark, docs):
    rng = random.Random(9)
    data = rows()
    for k in range(12):  # chains of texts that drift away from each other
        w = prose(rng, 60 + 20 * k).split()
        for step in range(8):
            w[rng.randrange(len(w))] = f"new{step}"
            data.append((1000 + 10 * k + step, " ".join(w), *data[0][2:]))
    got = {}
    for r in bagminhash.classes(spark.createDataFrame(data, SCHEMA)).where("class_id is not null").collect():
        got.setdefault(r["class_id"], []).append(r["doc_id"])
    want = [x for x in brute_classes(data) if x != [None]]
    assert sorted((sorted(x, key=str) for x in got.values() if x != [0]), key=str) == want


def test_one_of_each_keeps_columns_and_representatives(docs, none):
    kept = bagminhash.one_of_each(docs)
    assert kept.columns == docs.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert ids.count(4) == 1 and 5 not in ids and 6 not in ids and None in ids and 0 in ids
    assert bagminhash.one_of_each(none).count() == 0 and bagminhash.classes(none).count() == 0


def test_signatures_estimate_weighted_jaccard():
    rng = np.random.default_rng(1)
    h = rng.integers(1, 2**63, 400, dtype=np.uint64)
    h.sort()
    a, b = rng.integers(1, 6, 400), rng.integers(1, 6, 400)
    b[:40] = 0
    keep = b > 0
    s1 = bagminhash.signatures(np.zeros(400, int), h, a, 1, 4096)
    s2 = bagminhash.signatures(np.zeros(keep.sum(), int), h[keep], b[keep], 1, 4096)
    true = shingles.overlap((h, a), (h[keep], b[keep]))
    assert abs((s1 == s2).mean() - true) < 0.03


def test_blocks_lose_no_link_of_a_bucket(spark):
    """A star whose centre is linked to none, and a ring: the rest of the bucket is still joined."""
    rng = random.Random(5)
    base = prose(rng, 200).split()
    data = []
    for k in range(30):
        w = list(base)
        for p in rng.sample(range(200), 4):
            w[p] = f"v{k}"
        data.append((k, " ".join(w), None, None, None, None, None, None))
    got = {r["doc_id"]: r["class_id"] for r in bagminhash.classes(spark.createDataFrame(data, SCHEMA)).collect()}
    want = brute_classes(data)
    found = {}
    for i, c in got.items():
        found.setdefault(c, []).append(i)
    assert sorted((sorted(x) for x in found.values()), key=str) == want


def test_split_by_loses_nothing(spark):
    df, keys = spark.range(1000).withColumn("__word", F.lit(1)), spark.range(0, 1000, 7).withColumnRenamed("id", "k")
    maybe, sure = split_by(df.drop("__word"), F.col("id"), keys, "k")
    assert maybe.count() + sure.count() == 1000
    assert {r["id"] for r in maybe.collect()} >= set(range(0, 1000, 7))


def test_line_dedup_keeps_the_first_carrier(docs, none):
    out = {r["doc_id"]: r for r in line_dedup.clean(docs).collect()}
    line = "Same line that stands on many sites."
    assert line in out[10]["text"] and out[10]["n_removed"] == 0
    assert all(line not in out[i]["text"] and out[i]["n_removed"] == 1 for i in range(11, 23))
    assert out[0]["text"] is None and out[0]["n_lines"] == 0 and out[1]["text"] == "" and out[9]["text"] == "a\n" * 50
    assert line_dedup.clean(docs).columns == [*docs.columns, "n_lines", "n_removed"]
    assert line_dedup.clean(docs).count() == docs.count() and line_dedup.clean(none).count() == 0


def test_top_k_is_exact(spark):
    rng = np.random.default_rng(2)
    v = rng.normal(size=(300, 12)).astype(float)
    data = [(i, v[i].tolist()) for i in range(300)] + [(100, v[100].tolist()), (400, None), (401, [float("nan")] * 12), (402, [None] * 12), (None, v[0].tolist()), (50, v[3].tolist()), (403, []), (404, v[7].tolist()), (405, (v[9] * 1e9).tolist())]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>").repartition(5)
    ok = [(i, [math.floor(256 * x) for x in e]) for i, e in data if i is not None and e is not None and all(x is not None and math.isfinite(x) for x in e)]
    want = []
    for q in sorted({i for i, _ in ok if i % 50 == 0}):
        qv = [e for i, e in ok if i == q]
        best = {}
        for i, e in ok:
            if i != q:
                s = max(sum(x * y for x, y in zip(e, p, strict=False)) for p in qv[:1])
                best[i] = max(best.get(i, -(2**62)), s)
        want += [(q, r + 1, i, s) for r, (i, s) in enumerate(sorted(best.items(), key=lambda x: (-x[1], x[0]))[:5])]
    got = sorted(tuple(r) for r in topk_search.top_k(df).collect())
    assert [g for g in got if g[0] != 50] == [w for w in want if w[0] != 50] and len(got) == len(want)
    assert topk_search.top_k(df.limit(0)).count() == 0


def test_top_k_of_large_components(spark):
    """Whole numbers beyond doubles' exactness, scores beyond a long, and components whose 256-fold is no double."""
    big = [1e30, -1e30, 3.7e18, 1e200, -1e307, 1e5, 123456789.123, 0.5, -2.25, 1e305]
    rng = random.Random(4)
    data = [(i, [rng.choice(big) if rng.random() < 0.3 else rng.uniform(-3, 3) for _ in range(6)]) for i in range(120)]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>").repartition(3)
    ok = [(i, [math.floor(256 * x) for x in e]) for i, e in data if all(math.isfinite(256 * x) for x in e)]
    want = []
    for q, qv in ok:
        if q % 50 == 0:
            s = [(i, max(-(2**63), min(2**63 - 1, sum(x * y for x, y in zip(qv, e, strict=True))))) for i, e in ok if i != q]
            want += [(q, r + 1, i, x) for r, (i, x) in enumerate(sorted(s, key=lambda x: (-x[1], x[0]))[:5])]
    assert sorted(tuple(r) for r in topk_search.top_k(df).collect()) == want


def test_min_cost_flow_is_optimal():
    rng = random.Random(1)
    for _ in range(20):
        m, n = rng.randrange(1, 6), rng.randrange(1, 6)
        supply = [rng.randrange(50) for _ in range(m)]
        room = resharding.even(sum(supply) + rng.randrange(10), n)
        flow = resharding.min_cost_flow(supply, room, [[int(i != j) for j in range(n)] for i in range(m)])
        assert [sum(r) for r in flow] == supply and all(sum(r[j] for r in flow) <= room[j] for j in range(n))
        stay = sum(flow[i][i] for i in range(min(m, n)))
        assert stay == sum(min(supply[i], room[i]) for i in range(min(m, n)))
    cost = [[4, 1], [2, 9]]
    assert resharding.min_cost_flow([5, 5], [5, 5], cost) == [[0, 5], [5, 0]]


def test_resharding_contract(docs, none):
    got = resharding.contract(docs).collect()
    assert len(got) == docs.count()
    want = Counter((r[0], len((r[1] or "").encode()) + 16, zlib.crc32((r[1] or "").encode())) for r in rows())
    assert Counter((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    for s in {r["shard"] for r in got}:
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    assert resharding.contract(none).count() == 0


def files(folder):
    return {str(f.relative_to(folder)): f.read_bytes() for f in folder.rglob("*.parquet")}


def test_rewriting_leaves_other_shards_alone(spark, tmp_path):
    """Three shards of 100 rows, some of the second's bytes go to the third: the first one's files keep their bytes, and no row is lost. Ids repeat."""
    data = spark.range(300).select((F.col("id") % 290).alias("doc_id"), F.lit("x" * 10).alias("text"), F.floor(F.col("id") / 100).cast("int").alias("home"), F.lit("k").alias("slot"))
    at = tmp_path / "layout"
    data.drop("slot").withColumnRenamed("home", "shard").write.partitionBy("shard").parquet(str(at))
    before = files(at)
    assigned, flow = resharding.assign(data, old=F.col("home"), n_old=3, n_new=3, capacities=[2600, 2600 - 26 * 8, 2600 + 26 * 8])
    assert flow[0][0] == 2600 and resharding.changed(assigned) == [1, 2]
    assert resharding.rewrite(data, assigned, str(at)) == [1, 2]
    after = files(at)
    assert {k: v for k, v in after.items() if k.startswith("shard=0")} == {k: v for k, v in before.items() if k.startswith("shard=0")}
    back = spark.read.parquet(str(at))
    assert Counter(r["doc_id"] for r in back.collect()) == Counter(r["doc_id"] for r in data.collect())
    assert {r["shard"]: r["count"] for r in back.groupBy("shard").count().collect()} == {0: 100, 1: 92, 2: 108}
    # A shard that loses all goes.
    assigned, _ = resharding.assign(data, old=F.col("home"), n_old=3, n_new=3, capacities=[7800, 0, 0])
    assert resharding.rewrite(data, assigned, str(at)) == [0, 1, 2] and spark.read.parquet(str(at)).select("shard").distinct().count() == 1


def test_levelling():
    assert resharding.level([10, 0], [5, 5], {0: [(2, "a"), (5, "b")]}) == [("b", 1)]
    assert resharding.level([10, 0], [5, 5], {}) == [] and resharding.level([5, 5], [5, 5], {0: [(1, "a")]}) == []


def test_resharding_is_even(spark):
    many = spark.range(20000).select(F.col("id").alias("doc_id"), F.repeat(F.lit("x"), (F.col("id") * 7919 % 400).cast("int")).alias("text"))
    sizes = [r["s"] for r in resharding.contract(many).groupBy("shard").agg(F.sum("size").alias("s")).collect()]
    assert len(sizes) == 40 and max(sizes) - min(sizes) < 200


def test_raking_meets_its_marginals():
    rng = np.random.default_rng(0)
    codes = [rng.integers(0, n, 200) for n in (7, 4, 3)]
    tokens = rng.integers(1, 1000, 200).astype(float)
    goals = mixing.targets(codes, tokens, mixing.POWERS)
    w = mixing.rake(codes, tokens, goals)
    for c, g in zip(codes, goals, strict=True):
        assert np.allclose(np.bincount(c, w, len(g)), g, atol=1e-8)
    r = mixing.rate(tokens, w, 0.4)
    assert abs(np.minimum(tokens, r * w).sum() - 0.4 * tokens.sum()) < 1e-6 * tokens.sum()


def test_distributed_raking_agrees(spark, monkeypatch):
    rng = random.Random(6)  # every cell holds documents, so the sweeps converge fast
    docs = spark.createDataFrame([(i, prose(rng, rng.choice([20, 60, 90])), ["en", "de", None][i % 3], f"s{i % 4}") for i in range(150)], "doc_id long, text string, lang string, source string")
    got = mixing.mix_to_targets(docs).select("doc_id", "__share", "__probability").collect()
    monkeypatch.setattr(mixing, "DRIVER_CELLS", 0)
    again = mixing.mix_to_targets(docs).select("doc_id", "__share", "__probability").collect()
    key = lambda r: (str(r[0]), r[2])
    for a, b in zip(sorted(got, key=key), sorted(again, key=key), strict=True):
        assert a[0] == b[0] and abs(a[1] - b[1]) < 1e-9 and abs(a[2] - b[2]) < 1e-9


def test_mixing_on_edges(docs, none):
    out = mixing.mix_to_targets(docs)
    assert out.count() == docs.count() and mixing.mix_to_targets(none).count() == 0
    assert all(r["__tokens"] == len((r["text"] or "").split()) for r in out.collect() if r["doc_id"] != 23)
    assert all(r["__kept"] and r["__probability"] == 1 for r in out.collect() if not (r["text"] or "").split())


def test_mixing_against_plain_python(spark):
    """Cells, targets, sweeps, rate, probabilities and draws by their definitions, the hash from another library."""
    rng = random.Random(12)
    data = [(i if i % 9 or i % 17 == 0 or i % 19 == 0 else None, None if i % 17 == 0 else "" if i % 19 == 0 else prose(rng, rng.choice([5, 60, 1100])) + "#" * rng.choice([0, 0, 40]), ["en", "de", None][rng.randrange(3)], f"s{rng.randrange(4)}") for i in range(160)]

    def topic(t):
        marks = sum((t or "").count(c) for c in "#*$%&|<>")
        n = len((t or "").split())
        return "marked" if marks and marks * 100 >= len(t) else "short" if n < 50 else "long" if n >= 1000 else "prose"

    tokens = Counter()
    for _, t, lang, source in data:
        tokens[source, lang, topic(t)] += len((t or "").split())
    total, weight = sum(tokens.values()), {}
    goals = []
    for d, power in enumerate((0.5, 0.7, 0.8)):
        g = Counter()
        for c, n in tokens.items():
            g[c[d]] += n
        raised = {k: (n / total) ** power if n else 0.0 for k, n in g.items()}
        goals.append({k: x / sum(raised.values()) for k, x in raised.items()})
    weight = {c: n / total for c, n in tokens.items()}
    for _ in range(500):
        worst = 0.0
        for d in range(3):
            have = Counter()
            for c, w in weight.items():
                have[c[d]] += w
            worst = max([worst, *(abs(have[k] - x) for k, x in goals[d].items() if have[k] > 0)])
            weight = {c: w * goals[d][c[d]] / have[c[d]] if have[c[d]] > 0 else w for c, w in weight.items()}
        if worst < 1e-10:
            break
    low, high = 0.0, 1e12
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if sum(min(n, mid * weight[c]) for c, n in tokens.items()) < 0.5 * total else (low, mid)
    mixed = mixing.mix_to_targets(spark.createDataFrame(data, "doc_id long, text string, lang string, source string"))
    got = {(r["doc_id"], r["text"]): r for r in mixed.collect()}
    draw = xxhash.xxh64(struct.pack("<i", 4), seed=42).intdigest()
    for i, t, lang, source in data:
        r, n, cell = got[i, t], len((t or "").split()), (source, lang, topic(t))
        p = min(1.0, high * weight[cell] / tokens[cell]) if n else 1.0
        assert r["__topic"] == cell[2] and abs(r["__probability"] - p) < 1e-6 and abs(r["__share"] - weight[cell]) < 1e-7
        key = str(i) if i is not None else t or ""
        assert r["__kept"] == ((xxhash.xxh64(key.encode(), seed=draw).intdigest() >> 11) / 2**53 < r["__probability"])
    told = {(r["dimension"], r["category"]): r for r in mixing.achieved(mixed).collect()}
    for d, name in enumerate(mixing.DIMENSIONS):
        for k, x in goals[d].items():
            assert abs(told[name, k]["target"] - x) < 1e-6
        assert abs(sum(r["expected"] for (n, _), r in told.items() if n == name) - 1) < 1e-6


def best_score(p, text):
    """Viterbi over whole text by definition, without trie or memo."""
    known = {s: x for i, (s, x) in enumerate(zip(p.pieces, p.scores, strict=True)) if i > 2 and not p.first_byte <= i < p.first_byte + 256}
    s = "".join("\0" if c == "▁" else "▁" if c == " " else c for c in " " + text)
    best = [0.0] + [-math.inf] * len(s)
    for i in range(len(s)):
        if s[i] not in known:
            best[i + 1] = max(best[i + 1], best[i] + p.unknown)
        for j in range(i + 1, min(len(s), i + 16) + 1):
            if s[i:j] in known:
                best[j] = max(best[j], best[i] + known[s[i:j]])
    return best[-1]


def test_pieces_round_trip_and_optimum(docs, none):
    p = unigram_pieces.load()
    texts = {str(r[0]): r[1] for r in rows()}
    for r in unigram_pieces.encode_documents(docs, p).collect():
        text = texts[str(r["doc_id"])]
        assert r["round_trip"]
        if text is None:
            assert r["ids"] is None and r["n_pieces"] == 0
        elif text:
            assert p.decode(r["ids"]) == text and abs(r["score"] - best_score(p, text)) < 1e-6
    assert unigram_pieces.encode_documents(none, p).count() == 0


def test_pieces_side_by_side_equal_one_by_one():
    p = unigram_pieces.load()
    rng = random.Random(11)
    texts = ["".join(rng.choices("ab é日🎉\n▁!.,\x00eing ", k=rng.randrange(90))) for _ in range(400)] + ["", " ", "▁", "🎉" * 63, "🎉" * 64, "x" * 200, "", "a  b"]
    for text, (score, ids) in zip(texts, p.encode_many(texts), strict=True):
        alone = [p.viterbi(c.replace(" ", unigram_pieces.MARK).encode()) for c in p.cut.findall(" " + text) if c != unigram_pieces.MARK] if text else []
        marks = text.count(unigram_pieces.MARK)
        if not marks:
            assert b"".join(ids_ for _, ids_ in alone) == ids.tobytes()
        assert p.decode(ids) == text and abs(score - sum(s for s, _ in alone) - marks * p.unknown) < 1e-6


def test_a_full_memo_changes_nothing(monkeypatch):
    monkeypatch.setattr(unigram_pieces, "MEMO", 5)
    monkeypatch.setattr(unigram_pieces, "BLOCK", 3)
    small, large = unigram_pieces.load(), unigram_pieces.load()
    texts = [f"some words {i} and {i % 7} others" for i in range(60)]
    got = [small.encode(t)[1].tolist() for t in texts]
    assert got == [ids.tolist() for _, ids in large.encode_many(texts)] and len(small.old) >= 5


def test_double_array_finds_its_keys():
    rng = random.Random(4)
    keys = sorted({bytes(rng.choices(range(256), k=rng.randrange(1, 5))) for _ in range(3000)})
    base, check, value = unigram_pieces.double_array(keys, list(range(len(keys))))
    for want, key in enumerate(keys):
        s = 0
        for c in key:
            t = base[s] + c + 1
            assert check[t] == s
            s = t
        assert value[s] == want


# Published licence texts and notices, as they are usually laid out.
MIT = """MIT License

Copyright (c) 2020 Someone

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE."""
ISC = """Copyright 2020 Someone

Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH
REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY
AND FITNESS."""
BSD2 = """Copyright (c) 2020, Someone
All rights reserved.

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution."""
BSD3 = BSD2 + """

3. Neither the name of the University of Somewhere nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission."""
APACHE = """# Copyright 2020 Someone
#
# Licensed under the Apache License, Version 2.0 (the "License");
# you may not use this file except in compliance with the License.
# You may obtain a copy of the License at
#
#     http://www.apache.org/licenses/LICENSE-2.0
#
# Unless required by applicable law or agreed to in writing, software"""
GNU = """ * prog - does things
 * Copyright (C) 2020 Someone
 *
 * This program is free software: you can redistribute it and/or modify
 * it under the terms of the GNU {0} as published by
 * the Free Software Foundation, either version {1} of the License, or
 * (at your option) any later version.
 *
 * This program is distributed in the hope that it will be useful,
 * but WITHOUT ANY WARRANTY; without even the implied warranty of
 * MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
 * GNU General Public License for more details."""
GNU_ONLY = """This library is free software; you can redistribute it and/or
modify it under the terms of the GNU Lesser General Public
License as published by the Free Software Foundation;
version 2.1 of the License."""
MPL = """/* This Source Code Form is subject to the terms of the Mozilla Public
 * License, v. 2.0. If a copy of the MPL was not distributed with this
 * file, You can obtain one at https://mozilla.org/MPL/2.0/. */"""
ZLIB = """This software is provided 'as-is', without any express or implied
warranty. In no event will the authors be held liable.

Permission is granted to anyone to use this software for any purpose,
including commercial applications, and to alter it and redistribute it
freely, subject to the following restrictions:

1. The origin of this software must not be misrepresented; you must not
   claim that you wrote the original software."""
PUBLISHED = [
    (MIT, ["MIT"]),
    (textwrap.indent(MIT, "// "), ["MIT"]),
    (MIT.replace("The above copyright notice and this permission notice shall be included in all\ncopies or substantial portions of the Software.\n\n", ""), ["MIT-0"]),
    ("\n\n".join(reversed(MIT.split("\n\n"))), []),
    (ISC, ["ISC"]),
    (ISC.replace(", provided that the above\ncopyright notice and this permission notice appear in all copies", ""), ["0BSD"]),
    (BSD2, ["BSD-2-Clause"]),
    (BSD3, ["BSD-3-Clause"]),
    ("\n\n".join(reversed(BSD3.split("\n\n"))), []),
    (APACHE, ["Apache-2.0"]),
    ("Apache License\n  Version 2.0, January 2004\n\n TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION\n", ["Apache-2.0"]),
    (GNU.format("General Public License", "3"), ["GPL-3.0-or-later"]),
    (GNU.format("General Public License", "2"), ["GPL-2.0-or-later"]),
    (GNU.format("Lesser General Public License", "2.1"), ["LGPL-2.1-or-later"]),
    (GNU.format("Affero General Public License", "3"), ["AGPL-3.0-or-later"]),
    (GNU_ONLY, ["LGPL-2.1-only"]),
    (MPL, ["MPL-2.0"]),
    (ZLIB, ["Zlib"]),
    ("This work is licensed under the GNU General Public License, version 3.", ["GPL-3.0-only"]),
    ("Licensed under the GNU General Public License, version 3 or later.", ["GPL-3.0-or-later"]),
    ("Distributed under the terms of the GNU GPL v3 or any later version", ["GPL-3.0-or-later"]),
    ("This is not licensed under the MIT License.", []),
    ("Released under\nthe MIT License.", ["MIT"]),
    ("Licensed under CC BY-NC 4.0.\nSPDX-License-Identifier: CC-BY-4.0", ["CC-BY-4.0", "CC-BY-NC-4.0"]),
    ("This text is licensed under a Creative Commons Attribution-ShareAlike 3.0 Unported License.", ["CC-BY-SA-3.0"]),
    ("x SPDX-License-Identifier: MIT", []),
    ("# SPDX-License-Identifier: GPL-2.0-or-later\nx", ["GPL-2.0-or-later"]),
    ("SPDX-License-Identifier: MIT-1", []),
    ("This is free and unencumbered software released into the public domain.", ["Unlicense"]),
    ("Nothing here. At all.", []),
    ("", []),
    (None, []),
]


def test_published_licence_texts(spark):
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(PUBLISHED)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in licences.scan(df).collect()}
    assert [(i, got[i]["licences"]) for i in range(len(PUBLISHED))] == [(i, want) for i, (_, want) in enumerate(PUBLISHED)]
    assert got[7]["sentence_ids"] == ["rights", "bsd_grant", "bsd_source", "bsd_binary", "bsd_endorse"] and got[7]["rules"] == ["bsd3_text"]
    assert got[0]["sentence_ids"] == ["mit_grant", "mit_include", "mit_as_is", "mit_liability"] and got[9]["rules"] == ["apache2_header"]


def test_licence_sql_agrees(spark, tmp_path):
    duckdb = pytest.importorskip("duckdb")
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate([*PUBLISHED, *((r[1], None) for r in rows())])], "doc_id long, text string")
    df.write.parquet(str(tmp_path / "documents"))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{tmp_path}/documents/*.parquet'")
    want = sorted(tuple(map(str, r)) for r in con.execute(licences.oracle()).fetchall())
    assert sorted(tuple(map(str, r)) for r in licences.scan(df).collect()) == want


def test_language_id(spark, docs, none):
    en, de = "the cat and the dog sat on this mat with that", "der hund und die katze sind nicht auf dem stuhl"
    rng = random.Random(0)
    data = [(i, " ".join(rng.choices((en if i % 2 else de).split(), k=40)), "en" if i % 2 else "de") for i in range(400)] + [(900, None, "en"), (901, "12 34", "de"), (902, "", None)]
    got = {r["doc_id"]: r for r in langid.identify(spark.createDataFrame(data, "doc_id long, text string, lang string")).collect()}
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 4 == 2) for i in got)
    assert all(got[i]["lang_pred"] == ("en" if i % 2 else "de") for i in range(400))
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (900, 901, 902))
    assert langid.identify(none).count() == 0 and langid.identify(docs).count() == docs.count()


def test_language_probabilities_by_definition(spark):
    """A prediction is the mean of the table's rows of all grams that hold a letter, through the softmax."""
    rng = random.Random(2)
    texts = [prose(rng, rng.randrange(1, 30)) for _ in range(20)] + ["é", "x", "Ünï cödé 12", "a" * 3000]
    model = langid.train([(t, ["en", "de", "fr"][i % 3]) for i, t in enumerate(texts)])

    def bucket(gram, salt):
        if all(c == 32 for c in gram):
            return None
        h = int.from_bytes(gram, "little") * salt & 0xFFFFFFFF
        h = (h ^ h >> 15) * 0x2C1B3C6D & 0xFFFFFFFF
        return 1 + (h ^ h >> 16) % (langid.BUCKETS - 1)

    got = {r["doc_id"]: r for r in langid.predict(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), model).collect()}
    for i, t in enumerate(texts):
        b = bytes(c | 32 if 65 <= c <= 90 else c if 97 <= c <= 122 or c > 127 else 32 for c in b"   " + t.encode() + b"    ")
        # The gaps of a text are spaces; a gram of spaces only has no letter.
        grams = [bucket(b[k : k + n], salt) for n, salt in ((3, 0x9E3779B1), (4, 0x85EBCA77)) for k in range(len(b) - n + 1)]
        at = [g for g in grams if g is not None]
        z = (model.table[at].astype(float).sum(0) / len(at) + model.bias) / model.temperature
        p = np.exp(z - z.max()) / np.exp(z - z.max()).sum()
        assert abs(got[i]["score"] - p.max()) < 1e-6 and got[i]["lang_pred"] == model.labels[int(p.argmax())]
        assert got[i]["rejected"] == (got[i]["score"] < model.threshold)


def test_language_sample_is_bounded(spark):
    """Null and equal ids, and equal rows, neither empty the sample nor swell it."""
    rng = random.Random(8)
    one = next(i for i in range(9) if zlib.crc32(str(i).encode()) % 4 != 2)
    for ids in (lambda i: None, lambda i: one, lambda i: i):
        data = [(ids(i), prose(rng, 9), ["en", "de", "fr"][i % 3]) for i in range(900)]
        got = Counter(lang for _, lang in langid.sample(spark.createDataFrame(data, "doc_id long, text string, lang string"), 60))
        assert set(got) == {"en", "de", "fr"} and max(got.values()) <= 20 and min(got.values()) >= 1
    same = spark.createDataFrame([(one, "same text", "en")] * 500, "doc_id long, text string, lang string")
    assert 1 <= len(langid.sample(same, 60)) <= 60
    assert len(langid.sample(spark.createDataFrame(data, "doc_id long, text string, lang string"), 600, sample_bytes=3000)) < 60


def test_context_tree_matches_its_definition(spark):
    """Counts, mixtures and predictions recomputed by plain recursion."""
    texts = ["abab abc", "ABAB abd", "the the the", "", None, "né né"]
    train = [((t or "").lower().encode(), i) for i, t in enumerate(texts) if zlib.crc32(str(i).encode()) % 5 != 1]
    counts = Counter()
    for t, _ in train:
        b = bytes(ctw.DEPTH) + t + b"\0"
        for i in range(ctw.DEPTH, len(b)):
            for d in range(ctw.DEPTH + 1):
                for k in range(8):
                    counts[(b[i - d : i], 1 << k | b[i] >> (8 - k), b[i] >> (7 - k) & 1)] += 1
    ctx = {(c, n) for c, n, _ in counts}

    def kt(c, n):
        z, o = counts[(c, n, 0)], counts[(c, n, 1)]
        return math.lgamma(z + 0.5) + math.lgamma(o + 0.5) - math.lgamma(z + o + 1) - math.log(math.pi)

    def weighted(c, n):
        kids = [bytes([x]) + c for x in range(256) if (bytes([x]) + c, n) in ctx] if len(c) < ctw.DEPTH else []
        return math.log(0.5) + np.logaddexp(kt(c, n), sum(weighted(k, n) for k in kids)) if kids else kt(c, n)

    def predict(context, n):
        p = 0.5
        for d in range(ctw.DEPTH, -1, -1):
            c = context[len(context) - d :]
            if (c, n) in ctx:
                z, o = counts[(c, n, 0)], counts[(c, n, 1)]
                leaf = not any((bytes([x]) + c, n) in ctx for x in range(256)) or d == ctw.DEPTH
                a = 1.0 if leaf else math.exp(kt(c, n) - math.log(2) - weighted(c, n))
                p = a * (o + 0.5) / (z + o + 1) + (1 - a) * p
        return p

    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in ctw.score(df).collect()}
    tokens = Counter(w for t, _ in train for w in t.split())
    total, v = sum(tokens.values()) + len(train), len(tokens) + 1
    for i, t in enumerate(texts):
        b, s = bytes(ctw.DEPTH) + (t or "").lower().encode() + b"\0", 0.0
        for j in range(ctw.DEPTH, len(b)):
            for k in range(8):
                p = predict(b[j - ctw.DEPTH : j], 1 << k | b[j] >> (8 - k))
                s += math.log10(p if b[j] >> (7 - k) & 1 else 1 - p)
        assert abs(got[i]["score"] - s) < 1e-4
        own = (t or "").lower().encode().split()
        base = sum(math.log10((tokens[w] + 0.5) / (total + 0.5 * (v + 1))) for w in own) + math.log10((len(train) + 0.5) / (total + 0.5 * (v + 1)))
        assert abs(got[i]["base_score"] - base) < 1e-9 and got[i]["train_tokens"] == total
        assert got[i]["n_tokens"] == len(own) + 1 and got[i]["n_known"] == sum(w in tokens for w in own) + 1


def test_context_tree_probabilities_sum_to_one_under_pruning():
    rng = np.random.default_rng(0)
    data = rng.choice(np.frombuffer(b"aabbc d", np.uint8), 3000)
    g, _ = ctw.grams(np.array([0, 3000]), data)
    levels = []
    for d in range(ctw.DEPTH + 1):
        k, n = np.unique(g & np.uint64((1 << (8 * d + 8)) - 1), return_counts=True)
        levels.append((k[n > 3], n[n > 3]) if d > 2 else (k, n))
    tree = ctw.Tree(levels)
    for context in np.unique(g >> np.uint64(8))[:20]:
        assert abs((10 ** tree.log10(context << np.uint64(8) | np.arange(256, dtype=np.uint64))).sum() - 1) < 1e-6


def test_word_tail_takes_the_join(docs, none, monkeypatch):
    whole = {(str(r["doc_id"]), round(r["base_score"], 9), r["n_known"]) for r in ctw.score(docs).collect()}
    monkeypatch.setattr(ctw, "HEAD_WORDS", 5)
    assert {(str(r["doc_id"]), round(r["base_score"], 9), r["n_known"]) for r in ctw.score(docs).collect()} == whole
    assert ctw.score(none).count() == 0


def test_lookup_finds_its_keys():
    rng = np.random.default_rng(1)
    for n in (0, 1, 7, 5000):
        keys = np.unique(rng.integers(0, 2**64, n, dtype=np.uint64))
        table = ctw.Lookup(keys, keys.astype(float))
        assert (table.find(keys) == np.arange(len(keys))).all()
        other = np.setdiff1d(np.concatenate([rng.integers(0, 2**64, 3000, dtype=np.uint64), np.array([2**64 - 1], np.uint64)]), keys)
        assert (table.find(other) == -1).all()


def test_rare_grams_take_the_join(docs, monkeypatch):
    """The grams that the workers hold are a cache: no score depends on their number, nor on how many subtrees are built at once."""
    whole = {(str(r["doc_id"]), r["n_tokens"]): r["score"] for r in ctw.score(docs).collect()}
    monkeypatch.setattr(ctw, "CAPACITY", 5)
    monkeypatch.setattr(ctw, "BUILT", 50)
    few = {(str(r["doc_id"]), r["n_tokens"]): r["score"] for r in ctw.score(docs).collect()}
    assert few.keys() == whole.keys() and all(abs(few[k] - whole[k]) < 1e-6 * abs(whole[k]) for k in whole)


def test_rule_statistics(spark, docs, none):
    labels = spark.createDataFrame([(i, i % 2) for i in range(30)], "doc_id long, quality int")
    extra = [(100, "a b c a b c x\n \na b c a b c x\n&& <|>\nz", *rows()[0][2:]), (101, "w " * 100, *rows()[0][2:]), (102, "A a A a\nA a A a", *rows()[0][2:])]
    data = spark.createDataFrame([*rows(), *extra], SCHEMA)
    texts = {str(r[0]): r[1] for r in [*rows(), *extra]}
    for r in iforest.judge(data, labels).collect():
        b = (texts[str(r["doc_id"])] or "").encode()
        w = b.split()
        windows = Counter(zip(w, w[1:], w[2:], strict=False))
        inside = {i + k for i, t in enumerate(zip(w, w[1:], w[2:], strict=False)) if windows[t] > 1 for k in range(3)}
        lines = [x for x in b.split(b"\n") if x.split()]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(len(x.decode()) for x in w), sum(b.count(c) for c in (b"#", b"*", b"$", b"%", b"&", b"|", b"<", b">")), len(lines) - len(set(lines)), len(inside))
        assert r["base_failed"] == (len(w) < 50 or 100 * len(inside) > 50 * len(w)) and not (r["base_failed"] and r["kept"])
    assert iforest.judge(none, labels).count() == 0 and iforest.judge(data, labels.limit(0)).count() == data.count()


def test_forest_finds_an_outlier():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(2000, 5))
    odd = np.vstack([x[:50], np.full((1, 5), 9.0)])
    s = iforest.Forest(x).scores(odd)
    assert s[-1] > s[:-1].max()


def test_steps_are_the_forest():
    rng = np.random.default_rng(3)
    sample = np.round(rng.normal(size=(500, 1)), 1)
    forest = iforest.Forest(sample, trees=20)
    x = np.concatenate([np.round(rng.normal(size=300), 1), forest.cut[forest.feature >= 0][:50], [-99.0, 99.0]])
    assert np.allclose(iforest.Steps(forest).scores(x), forest.scores(x[:, None]))


def test_path_lengths_by_definition():
    """A walk from the root of each tree, one row at a time."""
    rng = np.random.default_rng(4)
    sample = rng.normal(size=(400, 3))
    f = iforest.Forest(sample, trees=10, size=64)

    def harmonic(n):
        return 0.0 if n < 2 else 1.0 if n == 2 else 2 * (math.log(n - 1) + 0.5772156649) - 2 * (n - 1) / n

    for x, s in zip(sample[:40], f.scores(sample[:40]), strict=True):
        total = 0.0
        for t in range(10):
            node = 0
            while f.feature[t, node] >= 0:
                node = 2 * node + (1 if x[f.feature[t, node]] <= f.cut[t, node] else 2)
            total += f.depth[t, node]
        assert abs(s - 2 ** (-total / 10 / harmonic(64))) < 1e-12


def test_thresholds_part_good_from_bad():
    rng = np.random.default_rng(5)
    good, bad = rng.uniform(0.3, 0.5, (1000, 3)), rng.uniform(0.3, 0.5, (100, 3))
    bad[:60, 1] += 0.3
    bad[60:, 2] += 0.3
    t = iforest.thresholds(good, bad, good)
    assert np.isinf(t[0]) and (bad / t).max(1).min() > 1 and (good / t).max(1).max() <= 1
    assert np.isinf(iforest.thresholds(good, good[:50], good)).all()
    alone = iforest.thresholds(good, bad[:0], good)
    assert abs(alone[0] - np.quantile(good[:, 0], 1 - iforest.MISSED)) < 1e-9 and np.isinf(alone[1:]).all()


def test_verdicts_by_definition(spark):
    """Scores and verdicts of judge() from the forests and thresholds of calibrate(), and bad rows told from good ones; ids that repeat or are null don't swell the samples."""
    rng = random.Random(6)
    data = [(i, prose(rng, 80) + ("".join(f" ##{k}|<>" for k in range(25)) if i % 10 == 0 else "")) for i in range(400)] + [(None, prose(rng, 70)), (1, prose(rng, 70))] * 30
    labels = spark.createDataFrame([(i, int(i % 10 != 0)) for i in range(0, 400)] + [(1, 1), (1, 1), (None, 0), (3, None)], "doc_id long, quality int")
    df = spark.createDataFrame(data, "doc_id long, text string")
    stats = iforest.statistics(df)
    forests, limits, (good, bad) = iforest.calibrate(stats, labels)
    got = iforest.judge(df, labels).collect()
    x = iforest.features(np.array([[r[c] for c in iforest.STATS] for r in got], np.int64))
    want = (forests.scores(x) / limits).max(1)
    assert np.allclose([r["score"] for r in got], want)
    assert all(r["kept"] == (not r["base_failed"] and s <= 1) for r, s in zip(got, want, strict=True))
    assert not any(r["kept"] for r in got if r["n_symbols"]) and sum(r["kept"] for r in got if not r["n_symbols"]) > 0.97 * sum(not r["n_symbols"] for r in got)
    told = iforest.held_out(df, labels).first()
    assert told["n_good"] == len(good) and told["n_bad"] == len(bad) > 0 and told["caught"] == 1 and told["lost"] < 0.05


def test_hot_keys_meet_by_broadcast(spark, monkeypatch):
    """However many keys are taken out, the rows are those of a plain join."""
    left = spark.range(3000).select(F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id") % 50).alias("k"), "id")
    right = spark.range(0, 60, 2).select(F.col("id").alias("k"), (F.col("id") * 2).alias("v"))
    counts = left.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    for how in ("inner", "left"):
        want = sorted(map(str, left.join(right, "k", how).collect()))
        for bound in (0, 1, 10, 1024):
            monkeypatch.setattr(common, "HOT", bound)
            hot = common.hot_keys(counts, ["k"])
            assert hot.count() <= bound
            assert sorted(map(str, common.join_hot(left, right, ["k"], hot, how).select("k", "id", "v").collect())) == want


def test_bins_bound_the_overlap_from_above():
    """Never under the true overlap, whatever the sizes; and tight enough to pass unrelated texts over."""
    rng = np.random.default_rng(7)
    sets = []
    for n in (1, 5, 40, 300, 380, 2000, 9000):
        for _ in range(3):
            h = np.unique(rng.integers(1, 2**63, n, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
            sets.append((h, rng.integers(1, 4, len(h))))
    for k in (6, 9, 12, 15):
        h, c = sets[k]
        keep = rng.random(len(h)) < 0.8
        sets.append((h[keep], c[keep]))
    sets.append((np.array([3], np.uint64), np.array([1 << 17])))
    bounds = bagminhash.Bounds([bagminhash.bins_of(*s).tobytes() for s in sets])
    every = np.arange(len(sets))
    passed = 0
    for i, a in enumerate(sets):
        js, bound = bounds.overlap(i, every, np.zeros(len(sets)))
        for j, b in zip(js, bound, strict=True):
            _, x, y = np.intersect1d(a[0], sets[j][0], return_indices=True)
            assert b >= np.minimum(a[1][x], sets[j][1][y]).sum()
        enough = 0.8 / 1.8 * np.array([a[1].sum() + s[1].sum() for s in sets])
        near, _ = bounds.overlap(i, every, enough)
        linked = [j for j in every if shingles.overlap(a, sets[j]) >= 0.8]
        assert set(linked) <= set(near.tolist())
        passed += len(every) - len(near)
    assert passed > 0.7 * len(sets) ** 2


def test_wide_buckets_in_small_blocks(spark, monkeypatch):
    """The classes don't depend on the size of the blocks, in rows or in shingles."""
    rng = random.Random(15)
    data = []
    for k in range(3):
        base = prose(rng, 150).split()
        for i in range(40):
            w = list(base)
            for p in rng.sample(range(150), 6):
                w[p] = f"z{i}"
            data.append((100 * k + i, " ".join(w)))
    df = spark.createDataFrame(data, "doc_id long, text string")
    whole = {(r["doc_id"], r["class_id"]) for r in bagminhash.classes(df).collect()}
    assert whole == {(i, min(c)) for c in brute_classes(data) for i in c}
    for rows_, shingles_ in ((7, 1 << 19), (512, 1000)):
        monkeypatch.setattr(bagminhash, "BLOCK", rows_)
        monkeypatch.setattr(bagminhash, "BLOCK_SHINGLES", shingles_)
        assert {(r["doc_id"], r["class_id"]) for r in bagminhash.classes(df).collect()} == whole


def test_hot_lines_change_nothing(spark, docs, monkeypatch):
    want = sorted(map(str, line_dedup.clean(docs).collect()))
    monkeypatch.setattr(common, "HOT", 0)
    assert sorted(map(str, line_dedup.clean(docs).collect())) == want


def test_line_counts_take_their_names(docs):
    out = line_dedup.clean(docs.withColumn("n_removed", F.lit(777)), counts=("a", "b"))
    assert out.columns == [*docs.columns, "n_removed", "a", "b"] and {r["n_removed"] for r in out.collect()} == {777}


def test_spooled_folders_go(spark):
    before = list(common.spooled)
    kept = common.spool(spark.range(5).toDF("x"), "test")
    path = common.spooled[-1]
    assert kept.count() == 5 and os.path.exists(path)
    common.discard(spark, [path])
    assert common.spooled == before and not os.path.exists(path)
    assert common.fresh(["a", "_A", "b"], "A") == "__A"


def test_language_arrays_are_bounded(spark):
    """A text of many pieces has the logits of one piece, in arrays of a piece's size; batches of texts are bounded in bytes."""
    import tracemalloc

    rng = random.Random(12)
    texts = [prose(rng, 40).encode() for _ in range(30)]
    model = langid.train([(t.decode(), ["en", "de", "fr"][i % 3]) for i, t in enumerate(texts)])
    rows = [*texts, b"", b"x", b" ".join(texts * 400), texts[0]]
    tracemalloc.start()
    got = model.logits(rows)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert sum(map(len, rows)) > 12 * langid.PIECE and peak < 6 * sum(map(len, rows)) + 100 * langid.PIECE
    assert np.allclose(got, np.concatenate([model.logits([t]) for t in rows]), atol=1e-12)
    whole, langid.PIECE = langid.PIECE, 37
    try:
        assert np.allclose(model.logits(rows[:33]), got[:33], atol=1e-12)
    finally:
        langid.PIECE = whole

    def count(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.nbytes])], ["n"])

    spark.conf.unset("spark.sql.execution.arrow.maxBytesPerBatch")
    docs = spark.range(0, 6000, 1, 1).selectExpr("id doc_id", "repeat('the cat ', 400) text", "'en' lang")
    langid.keep_recognised(docs, model)
    assert max(r["n"] for r in docs.mapInArrow(count, "n long").collect()) < 1.2 * common.BATCH_BYTES


def test_thresholds_of_all_rows(spark):
    """Histograms give the thresholds that all rows in memory give, for more rows than any cap."""
    rng = np.random.default_rng(7)
    on = lambda x: np.round(x * iforest.GRID) / iforest.GRID
    good, bad = on(rng.uniform(0.3, 0.6, (25_000, 2))), on(rng.uniform(0.3, 0.6, (300, 2)))
    bad[:200, 1] += 0.25
    for b in (bad, bad[:0]):
        x, flag = np.concatenate([good, b]), np.arange(len(good) + len(b)) < len(good)
        at = pa.array(np.arange(len(x) + 1) * 2, pa.int32())
        df = spark.createDataFrame(pa.table({"good": pa.array(flag), "scores": pa.ListArray.from_arrays(at, pa.array(x.ravel()))}))
        assert np.allclose(iforest.thresholds_of(df, good), iforest.thresholds(good, b, good), rtol=0, atol=1e-12)
