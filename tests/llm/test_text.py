"""Operators on texts, against plain versions on small tables."""

import random
import re
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from bicommunity.llm import licenses, packing, quality, simhash, substring, wordpiece
from bicommunity.llm.components import connected_components

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall(text or "")


def plain_fingerprint(text):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = words(low)
    if not w:
        return 0
    sh = [" ".join(w)] if len(w) < 3 else [" ".join(w[i : i + 3]) for i in range(len(w) - 2)]
    hs = [xxhash.xxh64(s.encode(), seed=42).intdigest() for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def plain_groups(fps):
    low = {}
    for d, f in fps:
        low[f] = min(low.get(f, d), d)
    group = {f: f for f in low}

    def find(f):
        while group[f] != f:
            f = group[f]
        return f

    nodes = sorted(low)
    for i, a in enumerate(nodes):
        for b in nodes[:i]:
            if bin(a ^ b).count("1") <= 3:
                group[find(a)] = find(b)
    first = {}
    for f in nodes:
        first[find(f)] = min(first.get(find(f), 1 << 65), low[f])
    return {f: first[find(f)] for f in nodes}


def test_simhash(spark, docs, none):
    rows = docs.filter("doc_id is not null").select("doc_id", "text").collect()
    want = plain_groups([(r.doc_id, plain_fingerprint(r.text)) for r in rows])
    got = simhash.near_duplicates(docs.filter("doc_id is not null")).collect()
    assert len(got) == len(rows)
    for r in got:
        text = next(x.text for x in rows if x.doc_id == r.doc_id)
        assert r.fp % (1 << 64) == plain_fingerprint(text)
        assert r.component_id == want[plain_fingerprint(text)]
    assert {r.component_id for r in got if r.doc_id in (2, 3, 4)} == {2}
    assert simhash.near_duplicates(docs).count() == docs.count()
    assert simhash.near_duplicates(none).count() == 0
    kept = [r.doc_id for r in simhash.keep_one(docs).collect()]
    assert {0, 2, 5, 6} <= set(kept) and not {3, 4} & set(kept) and None in kept
    assert simhash.keep_one(docs).columns == docs.columns or set(simhash.keep_one(docs).columns) == set(docs.columns)


@pytest.mark.parametrize("hot", [1, 4, 2048])
def test_links_span_all_groups(spark, hot):
    rng = random.Random(3)
    fps = set()
    for _ in range(12):
        base = rng.getrandbits(64)
        for _ in range(8):
            f = base
            for _ in range(rng.randrange(4)):
                f ^= 1 << rng.randrange(64)
            fps.add(f)
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    pairs = simhash.links(spark.createDataFrame([(f,) for f in signed], "fp bigint"), hot)
    for r in pairs.collect():
        assert bin((r.a ^ r.b) % (1 << 64)).count("1") <= 3
    roots = {r.node % (1 << 64): r.root for r in connected_components(pairs).collect()}
    want = plain_groups([(f, f) for f in fps])
    for a in fps:
        for b in fps:
            assert (roots.get(a, a) == roots.get(b, b)) == (want[a] == want[b])


def plain_removed(rows, n):
    first = {}
    for d, t in rows:
        w = words(t)
        for i in range(len(w) - n + 1):
            k = tuple(w[i : i + n])
            first[k] = min(first.get(k, d), d)
    out = []
    for d, t in rows:
        w = words(t)
        gone = [False] * len(w)
        for i in range(len(w) - n + 1):
            if first[tuple(w[i : i + n])] < d:
                gone[i : i + n] = [True] * n
        out.append((d, len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)))
    return sorted(out)


@pytest.mark.parametrize("batches", [1, 4])
def test_substring(spark, docs, none, batches):
    rng = random.Random(batches)
    pool = [[f"p{j}_{i}" for i in range(rng.randrange(8, 40))] for j in range(6)]
    rows = [(r.doc_id, r.text) for r in docs.filter("doc_id is not null").collect()]
    for d in range(20, 60):
        parts = []
        for _ in range(rng.randrange(1, 5)):
            parts += rng.choice(pool) if rng.random() < 0.7 else [f"u{d}_{i}" for i in range(rng.randrange(1, 20))]
        rows.append((d, " ".join(parts)))
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("resolved", F.lit(1))
    got = substring.dedup_windows(df, window=12, batches=batches)
    assert sorted((r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in got.collect()) == plain_removed(rows, 12)
    assert substring.dedup_windows(none).count() == 0
    assert substring.dedup_windows(docs).count() == docs.count()


def passages(seed, docs):
    rng = random.Random(seed)
    pool = [[f"p{j}_{i}" for i in range(rng.randrange(8, 40))] for j in range(6)]
    common = [f"c{i}" for i in range(25)]
    rows = []
    for d in docs:
        parts = common + [f"x{d}"] if rng.random() < 0.5 else []
        for _ in range(rng.randrange(1, 5)):
            parts += rng.choice(pool) if rng.random() < 0.7 else [f"u{d}_{i}" for i in range(rng.randrange(1, 20))]
        rows.append((d, " ".join(parts)))
    return rows


@pytest.mark.parametrize("hot", [1, 1024])
def test_calls_with_one_index_equal_one_call(spark, hot):
    """Five calls, with partial overlaps and compaction in between, and the index opened anew half way."""
    rows = passages(9, range(60))
    index = substring.WindowIndex(spark, 12, fan_in=3, hot_rows=hot)
    out, most = [], 0
    for lo in range(0, 60, 12):
        part = spark.createDataFrame(rows[lo : lo + 12], "doc_id bigint, text string")
        out += [(r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in substring.dedup_windows(part, window=12, batches=1, index=index).collect()]
        most = max(most, len(index.runs))
        index = substring.WindowIndex.opened(spark, index.manifest())
    assert sorted(out) == plain_removed(rows, 12)
    assert most == 2 and len(index.runs) == 1
    if hot == 1:
        assert all(r.hot for r in index.runs)


def test_runs_are_not_exchanged(spark):
    """A later batch reads a run in its buckets: neither exchanged nor sorted again."""
    rows = passages(10, range(40))
    index = substring.WindowIndex(spark, 12, fan_in=9)
    for lo in (0, 20):
        index.add(spark.createDataFrame(rows[lo : lo + 20], "doc_id bigint, text string"))
    own = index.table(index.runs[1].windows, index.WINDOWS).groupBy("anchor").agg(F.count("*").alias("n"))
    index.runs = index.runs[:1]
    with substring._in_order(spark):
        known = index.known(own)._jdf.queryExecution().executedPlan().toString()
    before = known[: known.index("FileScan")]
    history = known[known.index("SortMergeJoin") :].splitlines()
    scan = next(i for i, line in enumerate(history) if "FileScan" in line and "part#" in line)
    assert not any("Exchange" in line or " Sort " in line for line in history[: scan + 1]), known
    assert "SortMergeJoin" in before


def test_contexts_do_not_depend_on_the_text():
    rng = random.Random(3)
    shared = [f"s{rng.randrange(999)}".encode() for _ in range(300)]
    texts = [[f"a{i}".encode() for i in range(n)] + shared + [f"b{i}".encode() for i in range(m)] for n, m in ((0, 7), (91, 0), (40, 200))]
    found = [substring._Text(t, 50).contexts() for t in texts]
    sets = [set(zip(a.tolist(), c.tolist())) for a, c, _, _ in found]
    assert len(sets[0] & sets[1] & sets[2]) >= 12


def test_long_text_and_clashing_columns(spark):
    """A text of 24 MB with a repeated passage, beside columns that are named like the operator's own."""
    rng = np.random.default_rng(4)
    long = " ".join(f"w{x}" for x in rng.integers(0, 1 << 40, 1_700_000).tolist())
    words = long.split(" ")
    rows = [(1, " ".join(words[1_000_000:1_000_090])), (2, long), (3, " ".join(words[-60:]))]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    for c in ("rest", "resolved", "repeated", "open", "tk", "anchor", "n_removed", "whole"):
        df = df.withColumn(c, F.col("doc_id") * 10)
    got = {r.doc_id: r for r in substring.dedup_windows(df, batches=2).drop("kept_text").collect()}
    assert [got[i].n_removed for i in (1, 2, 3)] == [0, 90, 60]
    assert [got[i].n_words for i in (1, 2, 3)] == [90, len(words), 60]
    assert all(got[i][c] == 10 * i for i in got for c in ("rest", "resolved", "repeated", "open", "tk", "anchor", "whole"))


def plain_padding(histogram, ends):
    return sum(n * (min(e for e in ends if e >= x) - x) for x, n in histogram.items())


def test_best_boundaries():
    from itertools import combinations

    rng = random.Random(4)
    for _ in range(20):
        h = {rng.randrange(1, 60): rng.randrange(1, 9) for _ in range(8)}
        for b in (1, 2, 3, 4):
            got = packing.best_boundaries(h, b)
            top = max(h)
            best = min(plain_padding(h, {*c, top}) for k in range(b) for c in combinations([x for x in h if x != top], min(k, len(h) - 1)))
            assert len(got) <= b and plain_padding(h, got) == best
    assert packing.best_boundaries({}, 4) == []


def test_packing(spark, docs, none):
    got = packing.pack(docs, max_length=64, n_buckets=3, token_budget=200, shard_rows=4).collect()
    total = Counter()
    for r in got:
        total[r.doc_id] += r.length
        assert r.length <= 64 and (r.bucket is None) == (r.length == 0)
    want = Counter()
    for r in docs.collect():
        want[r.doc_id] += len(words(r.text))
    assert total == want
    seats = Counter((r.bucket, r.batch, r.slot) for r in got if r.bucket is not None)
    assert max(seats.values()) == 1
    by_batch = Counter()
    for r in got:
        if r.bucket is not None:
            by_batch[r.bucket, r.batch] += r.padded_length
    assert max(by_batch.values()) <= 200
    full = {b for b, _ in by_batch}
    for b in full:
        batches = sorted(k[1] for k in by_batch if k[0] == b)
        assert batches == list(range(len(batches)))
    assert packing.pack(none).count() == 0


def plain_tokens(word, pieces):
    n, i = 0, 0
    while i < len(word):
        for j in range(len(word), i, -1):
            if word[i:j] in pieces:
                n, i = n + 1, j
                break
        else:
            n, i = n + len(word[i].encode()), i + 1
    return n


def test_longest_match():
    rng = random.Random(8)
    for _ in range(40):
        pieces = {"".join(rng.choice("abcé") for _ in range(rng.randrange(1, 6))) for _ in range(rng.randrange(1, 25))}
        m = wordpiece.LongestMatch(sorted(pieces))
        for _ in range(60):
            w = "".join(rng.choice("abcéz") for _ in range(rng.randrange(0, 15)))
            assert m.pieces(w) == plain_tokens(w, pieces)


def test_token_counts(spark, docs, none):
    pieces = set(wordpiece.load_pieces())
    got = wordpiece.token_counts(docs).collect()
    want = Counter((r.doc_id, len(words(r.text)), sum(plain_tokens(wordpiece.WORD_START + w, pieces) for w in words(r.text))) for r in docs.collect())
    assert Counter(map(tuple, got)) == want
    assert wordpiece.token_counts(none, pieces=["a"]).count() == 0


def plain_counts(text):
    t = text or ""
    w = words(t)
    windows = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    repeat = {j for i in range(len(w) - 4) if windows[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
    seen, dup = set(), 0
    for line in t.split("\n"):
        if words(line):
            dup += line in seen
            seen.add(line)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(repeat)


def test_base_counts(docs):
    rng = random.Random(6)
    texts = [r.text for r in docs.collect()]
    texts += [" ".join(rng.choice("abé") for _ in range(rng.randrange(30))) for _ in range(50)]
    texts += [" ".join(str(i) for i in range(5000)) + " 1 2 3 4 5 6"]
    for t in texts:
        assert quality.base_counts(t.encode() if t is not None else None) == plain_counts(t)


def test_quality(spark, docs, none):
    rng = random.Random(2)
    good = [(i, " ".join(rng.choice(["the", "river", "house", "green", "walks", "over"]) + rng.choice(["", "s"]) for _ in range(40)), 1) for i in range(60)]
    bad = [(100 + i, " ".join(rng.choice(["THE", "RIV", "ER"]) + rng.choice(["!!", "$$$", "%%%"]) + str(rng.randrange(90)) for _ in range(40)), 0) for i in range(60)]
    df = spark.createDataFrame([(i, t) for i, t, _ in good + bad], "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, q) for i, _, q in good[:40] + bad[:40]], "doc_id bigint, quality int")
    model = quality.train(df, labels)
    kept = {r.doc_id: r.kept for r in quality.judge(df, model).collect()}
    held = good[40:] + bad[40:]
    assert np.mean([kept[i] == bool(q) for i, _, q in held]) > 0.95
    assert quality.train(df, labels.limit(0)) is None and quality.train(none, labels) is None
    plain = quality.judge(docs, None)
    assert plain.count() == docs.count() and {r.kept for r in plain.filter("n_words < 10").collect()} == {False}
    assert quality.judge(none, model).count() == 0 and quality.train(df, labels.limit(3)) is None


def test_licenses(spark, docs, none):
    mit = "Permission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files (the \"Software\"), to deal\nin the Software without restriction, including without limitation the rights\nto use, copy, modify, merge, publish, distribute, sublicense, and/or sell\ncopies of the Software, and to permit persons to whom the Software is\nfurnished to do so, subject to the following conditions"
    rows = [(1, "Some text.\nReleased under the MIT License."), (2, "x y\nLicensed under the Apache License, Version 2.0.\nAll rights reserved."), (3, None), (4, "no licence here"), (5, mit), (6, "released under the mit license of another kind")]
    got = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert got[1].licenses == ["MIT"] and got[2].licenses == ["Apache-2.0", "all-rights-reserved"]
    assert got[2].sentences == ["apache_notice", "rights_reserved"]
    assert got[3].licenses == got[4].licenses == got[6].licenses == []
    assert licenses.scan(docs).count() == docs.count() and licenses.scan(none).count() == 0
    known = set(licenses.SENTENCES)
    assert all(set(r) <= known for _, r in licenses.RULES)
    assert all(licenses.normalise(s) == s for s in licenses.SENTENCES.values())


MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy
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
APACHE = """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License."""
GPL3 = """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details."""
GPL2 = GPL3.replace("software: you", "software; you").replace("version 3", "version 2")
BSD = """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.
%s
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED."""
BSD2, BSD3 = BSD % "", BSD % """
3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.
"""


def test_licenses_of_whole_texts(spark):
    """Every rule fires: whole texts wrapped, as comments and on one line; notices on a line between others."""
    import duckdb

    from bicommunity.llm import licenses

    rows = []
    for name, text in [("MIT", MIT), ("Apache-2.0", APACHE), ("GPL-3.0-or-later", GPL3), ("GPL-2.0-or-later", GPL2), ("BSD-2-Clause", BSD2), ("BSD-3-Clause", BSD3)]:
        comment = "/*\n" + "\n".join(f" * {line}".rstrip() for line in text.split("\n")) + "\n */"
        rows += [(name, t) for t in (text, comment, " ".join(text.split()), text.replace("2.0\n\nUnless", "2.0 Unless").replace("at\n\n ", "at\n"), text.replace("http:", "https:"))]
    rows += [(name, f"Some words\n{licenses.SENTENCES[only[0]].capitalize()}\nOther words") for name, only in licenses.RULES if len(only) == 1]
    docs = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(rows)], "doc_id bigint, text string")
    got = {r.doc_id: r for r in licenses.scan(docs).collect()}
    assert [(i, rows[i][0], got[i].licenses) for i in range(len(rows)) if got[i].licenses != [rows[i][0]]] == []
    con = duckdb.connect()
    con.execute("CREATE TABLE documents (doc_id BIGINT, text VARCHAR)")
    con.executemany("INSERT INTO documents VALUES (?, ?)", [(i, t) for i, (_, t) in enumerate(rows)])
    said = {r[0]: r[1:] for r in con.execute(licenses.scan_sql()).fetchall()}
    assert said == {i: (",".join(r.licenses), r.rules, ",".join(r.sentences)) for i, r in got.items()}


def test_window_hashes_of_a_batch_are_written_once(spark, monkeypatch):
    """Beside the new run no table of a batch holds the hashes of its windows."""
    seen = {}
    remove = substring.remove
    monkeypatch.setattr(substring, "remove", lambda s, path: (seen.update({path: s.read.parquet(path).columns}), remove(s, path)))
    words = [f"w{i}" for i in range(80)]
    df = spark.createDataFrame([(i, " ".join(words[i:])) for i in range(4)], "doc_id bigint, text string")
    got = {r.doc_id: r.n_removed for r in substring.dedup_windows(df, window=12, batches=1).collect()}
    found = [c for path, c in seen.items() if path.endswith("-found")]
    assert found == [["anchor", "context", "doc_id"]] and got == {0: 0, 1: 79, 2: 78, 3: 77}
