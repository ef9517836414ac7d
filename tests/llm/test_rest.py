"""Vectors, conversations, mixing, language and the pipeline."""

import hashlib
import math
import random

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from bicommunity.llm import ann, chat, joins, langid, mixing


def test_probe_order_is_by_cost():
    rng = np.random.default_rng(1)
    for _ in range(5):
        inside = rng.random(4)
        got = ann.probe_order(inside, 81)
        assert len({tuple(x) for x in got.tolist()}) == len(got) == 81
        cost = [sum((inside[i] if s < 0 else 1 - inside[i]) ** 2 for i, s in enumerate(x) if s) for x in got.tolist()]
        assert cost == sorted(cost)


def test_nearest(spark):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((600, 16)).astype(np.float32)
    x[40:120] = x[7]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    odd = [(700, None), (800, [0.0] * 16), (900, [math.nan] + [1.0] * 15), (1000, [None] + [1.0] * 15), (1100, [1.0] * 3), (1200, [math.inf] * 16)]
    df = spark.createDataFrame(rows + odd, "vec_id bigint, embedding array<float>").withColumn("score", F.lit(1))
    got = {}
    for r in ann.nearest(df, df.filter("vec_id % 20 = 0")).collect():
        got.setdefault(r.query_id, []).append(r)
    assert sorted(got) == list(range(0, 600, 20))
    d = x.astype(np.float64)
    hits = []
    for q, rs in got.items():
        rs.sort(key=lambda r: r["rank"])
        assert [r["rank"] for r in rs] == list(range(1, 11))
        dist = np.sqrt(((d - d[q]) ** 2).sum(axis=1))
        assert all(abs(r.score - dist[r.vec_id]) < 1e-12 and r.vec_id != q for r in rs)
        assert [(r.score, r.vec_id) for r in rs] == sorted((r.score, r.vec_id) for r in rs)
        want = [i for i in np.lexsort((np.arange(600), dist)) if i != q][:10]
        hits.append(len(set(want) & {r.vec_id for r in rs}) / 10)
        if q in range(40, 120):
            assert [r.vec_id for r in rs] == want
    assert np.mean(hits) >= 0.9
    few = df.filter("vec_id < 4")
    assert ann.nearest(few, few.filter("vec_id = 0")).count() == 3
    assert ann.nearest(df.limit(0), df).count() == 0


def events(spark, rows):
    return spark.createDataFrame(rows, "conv_id bigint, seq bigint, event string, message_id string, role string, text string")


def test_fold(spark):
    log = [
        (1, 1, "message", "a", "user", "hi"),
        (1, 2, "message", "b", "assistant", "wro"),
        (1, 3, "delta", "b", None, "ng"),
        (1, 4, "regenerate", "b", None, "ignored"),
        (1, 5, "delta", "b", None, "ri"),
        (1, 6, "delta", "b", None, "ght"),
        (1, 7, "edit", "a", None, "hello"),
        (1, 8, "message", "c", "user", "gone"),
        (1, 9, "delete", "c", None, None),
        (2, None, "delta", "z", "assistant", None),
    ]
    out = {r.conv_id: r for r in chat.format_log(events(spark, log)).collect()}
    assert out[1].formatted == "<|im_start|>user\nhello<|im_end|>\n<|im_start|>assistant\nright<|im_end|>\n"
    assert out[2].formatted == "<|im_start|>assistant\n<|im_end|>\n"
    assert [s.text for s in out[1].segments if s.loss] == ["right"]
    assert chat.format_log(events(spark, [])).count() == 0


def test_round_trip(spark):
    rng = random.Random(5)
    bits = ["<|im_end|>", "<|im_start|>", "&lt;|", "&amp;", "\n", "|>", "<", "assistant", "é", "&#10;", "\\"]
    rows = []
    for c in range(6):
        for t in range(rng.randrange(1, 9)):
            rows.append((c, t % 5, rng.choice(["user", "assistant", "sys\ntem", None]), rng.choice([None, "", "".join(rng.choice(bits) for _ in range(12))])))
    df = spark.createDataFrame(rows, "conv_id bigint, turn int, role string, text string").withColumn("seq", F.lit(1))
    out = chat.format_log(chat.log_of_turns(df)).withColumn("turns", chat.turns(F.col("formatted"))).withColumn("lossy", chat.loss_text(F.col("segments")))
    got = {r.conv_id: r for r in out.collect()}
    for c in got:
        mine = sorted((t, r is not None, r or "", x is not None, x or "") for cc, t, r, x in rows if cc == c)
        assert [(t.role, t.text) for t in got[c].turns] == [(m[2], m[4]) for m in mine]
        assert got[c].lossy == "".join(m[4] for m in mine if m[2] == "assistant")


def test_sha(spark):
    df = spark.createDataFrame([("é\n",)], "t string")
    assert df.select(chat.sha256(F.col("t"))).first()[0] == hashlib.sha256("é\n".encode()).hexdigest()


def plain_targets(sizes, weights, share, most):
    names = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    left, fixed = share * sum(sizes.values()), {}
    while True:
        open_ = [s for s in names if s not in fixed]
        total = sum(w[s] for s in open_)
        over = [s for s in open_ if left * w[s] / total > most * sizes[s] + 1e-9]
        if not over:
            return fixed | {s: left * w[s] / total for s in open_}
        for s in over:
            fixed[s] = most * sizes[s]
        left = share * sum(sizes.values()) - sum(fixed.values())


def test_mixing(spark, docs, none):
    rng = random.Random(1)
    rows = [(i, " ".join(["w"] * rng.randrange(0, 60)), rng.choice(["a", "b", "b", "b", "é", None])) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    got = mixing.mix(df).collect()
    assert sorted(r.doc_id for r in got) == list(range(400))
    sizes = {}
    for i, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len(t.split())
    want = plain_targets(sizes, (3, 1, 2), 1.5, 2)
    for s in sizes:
        mine = [r for r in got if r.source == s]
        assert all(abs(r.target - want[s]) < 1e-6 * max(1, want[s]) and r.source_size == sizes[s] for r in mine)
        assert abs(sum(r.size * r.copies for r in mine) - want[s]) <= 60
        assert all(0 <= r.copies <= 2 for r in mine)
    again = mixing.mix(df.repartition(7)).collect()
    assert sorted((r.doc_id, r.copies) for r in got) == sorted((r.doc_id, r.copies) for r in again)
    assert mixing.mix(docs).count() == docs.count() and mixing.mix(none).count() == 0
    out = mixing.mixed_rows(docs)
    assert set(out.columns) == set(docs.columns)
    assert out.count() == mixing.mix(docs).agg(F.sum("copies")).first()[0]


def test_language(spark, docs, none):
    from bicommunity.llm.store import read

    real = read(spark, "/root/testdata/sf0.001", "documents")
    model = langid.train(real)
    assert model.languages == tuple(sorted(r.lang for r in real.select("lang").distinct().collect()))
    got = langid.identify(langid.document_evidence(real).withColumn("truth", F.lit(1)), model).collect()
    truth = {r.doc_id: r.lang for r in real.collect()}
    assert np.mean([r.lang == truth[r.id] for r in got]) > 0.95
    pages = read(spark, "/root/testdata/sf0.001", "pages")
    found = langid.identify(langid.page_evidence(pages), model)
    assert found.count() == pages.count()
    assert np.mean([r.lang == r.declared for r in found.collect()]) > 0.9
    assert langid.identify(langid.document_evidence(docs), model).count() == docs.count()
    assert langid.identify(langid.document_evidence(none), model).count() == 0
    assert langid.visible(b"<p>a&amp;b<script>x</script><!-- c --></p>").split() == [b"a&b"]
    flat = langid.identify(langid.document_evidence(spark.createDataFrame([(1, None, None)], "doc_id bigint, text string, source string")), model).first()
    assert flat.lang in model.languages


def plain_fusion(rows, model, smoothing):
    """Posterior of each row (id, text, declared, host), from the definition."""
    n = len(model.languages)

    def softmax(x):
        e = np.exp(np.array(x) - max(x))
        return e / e.sum()

    def levels(host):
        parts = host.split(".") if host is not None else []
        return (".".join(parts[-2:]), parts[-1]) if len(parts) > 1 else (None, None)

    logs = [model.likelihood(t.encode() if t is not None else None) for _, t, _, _ in rows]
    soft = [softmax(x) for x in logs]
    code = [None if d is None else d if d in model.languages else "other" for _, _, d, _ in rows]
    groups = {}
    for i, (_, _, _, host) in enumerate(rows):
        domain, suffix = levels(host)
        for key in (("host", host), ("domain", domain), ("suffix", suffix), ("code", code[i])):
            if key[1] is not None:
                groups[key] = groups.get(key, np.zeros(n)) + soft[i]
    base = sum(soft) + 1.0
    out = []
    for i, (_, _, _, host) in enumerate(rows):
        domain, suffix = levels(host)
        log, prior = np.array(logs[i]), base / base.sum()
        for key in (("suffix", suffix), ("code", code[i])):
            if key[1] is not None:
                own = np.maximum(groups[key] - soft[i], 0)
                log = log + np.log((own + smoothing * own.sum() / base.sum() + 1e-3) / (base + smoothing))
        for key in (("domain", domain), ("host", host)):
            if key[1] is not None:
                own = np.maximum(groups[key] - soft[i], 0)
                prior = (own + smoothing * prior) / (own.sum() + smoothing)
        out.append(softmax(log + np.log(prior)))
    return out


def test_fusion_equals_its_definition(spark):
    rng = np.random.default_rng(4)
    model = langid.TextModel(("de", "en", "fr"), np.log(rng.dirichlet([1] * 3, 1 << langid.BITS)))
    hosts = [None, "a.b.de", "c.b.de", "b.de", "x.com", "y.x.com", "local", "q.com"]
    rows = [(i, None if i % 11 == 0 else " ".join("".join(rng.choice(list("abcdefgh"), 3)) for _ in range(i % 4)), [None, "de", "en", "xx"][i % 4], hosts[int(rng.integers(len(hosts)))]) for i in range(80)]
    want = plain_fusion(rows, model, 5.0)
    df = spark.createDataFrame(rows, "id bigint, text string, declared string, host string").withColumn("markup", F.lit(False)).withColumn("soft", F.lit("own")).withColumn("n", F.lit(7))
    for least in (1, 1024):
        langid_least, joins.LEAST = joins.LEAST, least
        try:
            got = {r.id: r for r in langid.identify(df, model).collect()}
        finally:
            joins.LEAST = langid_least
        assert len(got) == len(rows)
        for (i, *_), w in zip(rows, want):
            assert abs(got[i].probability - w.max()) < 1e-9 and got[i].lang == model.languages[int(w.argmax())]
            assert got[i].soft == "own" and got[i].n == 7


def test_language_on_texts_that_were_not_seen(spark):
    from bicommunity.llm.store import read

    real = read(spark, "/root/testdata/sf0.01", "documents")
    model = langid.train(real.filter("doc_id % 3 <> 0"), 60)
    held = real.filter("doc_id % 3 = 0 and length(text) > 40")
    truth = {r.doc_id: r.lang for r in held.collect()}
    got = langid.identify(langid.document_evidence(held), model).collect()
    assert np.mean([r.text_lang == truth[r.id] for r in got]) > 0.97
    rare = real.filter("lang = 'en'").withColumn("lang", F.when(F.col("doc_id") == real.filter("lang = 'en'").agg(F.min("doc_id")).first()[0], "zz").otherwise(F.col("lang")))
    assert "zz" in langid.train(rare, 5).languages


def test_language_without_labels_and_long_tags(spark, none):
    empty = langid.train(none)
    assert empty.languages == ()
    docs = spark.createDataFrame([(1, "text", "s")], "doc_id bigint, text string, source string")
    got = langid.identify(langid.document_evidence(docs), empty).collect()
    assert [(r.id, r.lang, r.probability) for r in got] == [(1, None, None)]
    page = "<html " + "data-x='y' " * 500 + "lang='FR'><body>x</body></html>"
    pages = spark.createDataFrame([(1, "http://a.b/c", page), (2, "::bad::", None)], "page_id bigint, url string, html string")
    assert [r.declared for r in langid.page_evidence(pages).orderBy("id").collect()] == ["fr", None]


def test_mixing_keeps_each_document_at_its_share(spark):
    """400 sources of the same seven sizes: a document's mean copies are what its target asks for, at any size."""
    sizes = (1, 2, 5, 9, 20, 70, 300)
    rows = [(s * 10 + i, " ".join(["w"] * n), f"s{s:03d}") for s in range(400) for i, n in enumerate(sizes)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id bigint, text string, source string"), weights=(1,), share=1.4).collect()
    for i in range(len(sizes)):
        mine = [r.copies for r in got if r.doc_id % 10 == i]
        assert set(mine) <= {1, 2} and abs(np.mean(mine) - 1.4) < 4 * 0.49 / 20


def test_mixing_shares_copies_among_repeated_rows(spark):
    rows = [(7, "a b c", "s", i % 2) for i in range(50)] + [(i, "x " * i, "s", 0) for i in range(20, 60)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string, uid int").withColumn("given", F.lit(3)).withColumn("part", F.lit(3)).repartition(5)
    got = mixing.mix(df).collect()
    mine = sorted(r.copies for r in got if r.doc_id == 7)
    assert len(got) == len(rows) and len(mine) == 50 and mine[-1] - mine[0] <= 1
    out = mixing.mixed_rows(df)
    assert out.columns == df.columns and out.filter("doc_id = 7").count() == sum(mine)
    assert out.count() == sum(r.copies for r in got)


def test_nearest_finds_enough_of_many(spark):
    """Recall of the ten nearest among 60,000 distinct vectors, against all distances."""
    rng = np.random.default_rng(12)
    x = rng.standard_normal((60_000, 16)).astype(np.float32) + rng.standard_normal((40, 16)).astype(np.float32)[np.arange(60_000) % 40]
    df = spark.createDataFrame(pd.DataFrame({"vec_id": np.arange(60_000), "embedding": x.tolist()}), "vec_id bigint, embedding array<float>")
    got = {}
    for r in ann.nearest(df, df.filter("vec_id % 600 = 0")).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    hits = []
    for q, mine in got.items():
        d = ((x.astype(np.float64) - x[q].astype(np.float64)) ** 2).sum(axis=1)
        d[q] = np.inf
        hits.append(len(mine & set(np.argsort(d, kind="stable")[:10].tolist())) / 10)
    assert len(got) == 100 and np.mean(hits) >= 0.9


def test_streamed_log_folds_back(spark):
    rows = [(1, 0, "user", "how are you"), (1, 1, "assistant", "fine"), (1, 2, "system", "x"), (1, 3, "assistant", None), (2, 0, None, "é<|im_end|>é"), (2, 1, "user", "")]
    log = chat.log_of_turns(spark.createDataFrame(rows, "conv_id bigint, turn int, role string, text string"))
    events = chat.streamed(log)
    assert {r.event for r in events.select("event").distinct().collect()} == {"message", "delta", "edit", "regenerate"}
    assert sorted(map(tuple, chat.fold(events).select("conv_id", "role", "text").collect())) == sorted((c, r or "", x or "") for c, _, r, x in rows)


def test_pipeline(spark):
    import corpus_pipeline as cp
    from bicommunity.llm.store import read

    sf = "/root/testdata/sf0.001"
    docs = read(spark, sf, "documents")
    now, counts = docs, [docs.count()]
    for name, stage in cp.STAGES[:-1]:
        now = stage(spark, now, sf)
        assert now.columns == docs.columns and now.dtypes == docs.dtypes, name
        counts.append(now.count())
    assert counts[0] > counts[1] >= counts[2] >= counts[3] > 0
    packed = cp.STAGES[-1][1](spark, now, sf)
    assert packed.filter("piece = 0").count() == counts[-1]
    assert [n for n, _ in cp.STAGES] == ["quality", "near_dedup", "substring_dedup", "mixing", "packing"]


def test_near_dedup_finds_resemblance(spark):
    """Groups of the stage against all pairs of exact five-word shingle sets, at both sides of 0.8."""
    import corpus_pipeline as cp

    def changed(words, at):
        return [f"new{i}" if i in at else w for i, w in enumerate(words)]

    rows, sets = [], {}
    for g in range(12):
        words = [f"g{g}w{i}" for i in range(104)]
        for d in range(4):
            rows.append((g * 10 + d, " ".join(changed(words, {7 + 20 * j for j in range(d + g % 2)}))))
    rows += [(500, ""), (501, None), (502, "a b"), (503, "A  b"), (None, rows[0][1])]
    for i, text in rows:
        w = (text or "").lower().split()
        sets[i] = {tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set()
    ids, group = sorted(i for i, _ in rows if i is not None), {}
    for i in ids:
        group[i] = i
    for i in ids:
        for j in ids:
            union = len(sets[i] | sets[j])
            if i < j and len(sets[i] & sets[j]) * 5 >= union * 4:
                low, high = sorted((group[i], group[j]))
                group = {k: low if v == high else v for k, v in group.items()}
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    kept = [r.doc_id for r in cp.near_dedup(spark, docs, "").collect()]
    assert sorted(k for k in kept if k is not None) == [i for i in ids if group[i] == i]
    assert kept.count(None) == 1
    assert cp.near_dedup(spark, docs.limit(0), "").count() == 0


def test_stages_take_clashing_columns_nulls_and_repeats(spark, none):
    """Each stage on a table whose columns are named like the operators' own, with nulls, blanks and repeated rows."""
    import corpus_pipeline as cp

    sf = "/root/testdata/sf0.001"
    words = [f"word{i % 31}{'abcdefg'[i % 7]}{i}" for i in range(120)]
    rows = [(1, " ".join(words), "a"), (1, " ".join(words), "a"), (2, " ".join(words[:119] + ["changed"]), "a"), (3, None, None), (4, "", "b"), (5, "a b c", "b"), (None, " ".join(words[::-1]), "b"), (6, " ".join(words[20:90] + ["x", "y"]), None), (8, " ".join(words[::2]), "a")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string, source string")
    names = ("original", "open", "tk", "resolved", "repeated", "rest", "row", "uid", "given", "part", "probability", "kept", "n_words", "n_removed", "kept_text", "base_failed", "node", "n", "size", "copies", "bucket", "length", "own", "nth", "take")
    for c in names:
        df = df.withColumn(c, F.concat(F.lit(c), F.coalesce(F.col("doc_id").cast("string"), F.lit("?"))))
    df = df.withColumn("n_chars", F.length("text").cast("int"))
    for name, stage in cp.STAGES:
        got = stage(spark, df, sf)
        assert stage(spark, df.limit(0), sf).count() == 0, name
        if name == "packing":
            continue
        assert got.dtypes == df.dtypes, name
        out = got.collect()
        assert all(r[c] == c + ("?" if r.doc_id is None else str(r.doc_id)) for r in out for c in names), name
        assert all(r.n_chars == (None if r.text is None else len(r.text)) for r in out), name
        if name == "near_dedup":
            assert sorted(r.doc_id for r in out if r.doc_id is not None) == [1, 3, 5, 6, 8] and len(out) == 6
        if name == "substring_dedup":
            assert {r.doc_id: len(r.text.split()) for r in out if r.text}[6] == 2


def test_training_does_not_depend_on_the_order_of_rows(spark):
    from bicommunity.llm import quality

    rng = random.Random(2)
    texts = [(i % 40, " ".join(rng.choice(["river", "house"] if i % 2 else ["$$$", "!!"]) + str(rng.randrange(9)) for _ in range(30))) for i in range(200)]
    df = spark.createDataFrame(texts, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id bigint, quality int")
    a, b = quality.train(df.orderBy("text"), labels), quality.train(df.orderBy(F.desc("text")), labels)
    assert np.array_equal(a.weights, b.weights) and (a.bias, a.slope, a.offset) == (b.bias, b.slope, b.offset)
    assert quality.train(df, labels, max_entries=10) is None


def test_fit_goes_by_pieces():
    """The classifier's fit on the driver holds little beside the vectors, and pieces give what one gives."""
    import tracemalloc

    from bicommunity.llm import quality

    rng = np.random.default_rng(3)
    start = np.r_[0, np.cumsum(rng.integers(0, 4000, 1500))].astype(np.int64)
    index, value = rng.integers(0, 1 << 16, start[-1]).astype(np.int32), rng.random(start[-1]).astype(np.float32)
    y = rng.integers(0, 2, 1500)
    tracemalloc.start()
    w, b = quality._logistic(index, value, start, y, 1 << 16, epochs=3)
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 12 * start[-1]
    row = np.repeat(np.arange(1500), np.diff(start))
    want, bias, g2, b2 = np.zeros(1 << 16), 0.0, np.full(1 << 16, 1e-8), 1e-8
    share = np.where(y == 1, 0.5 / y.sum(), 0.5 / (1500 - y.sum()))
    for _ in range(3):
        g = share * (1 / (1 + np.exp(-(np.bincount(row, want[index] * value, 1500) + bias))) - y)
        gw = np.bincount(index, g[row] * value, 1 << 16) + 1e-5 * want
        g2, b2 = g2 + gw * gw, b2 + g.sum() ** 2
        want, bias = want - 0.5 * gw / np.sqrt(g2), bias - 0.5 * g.sum() / np.sqrt(b2)
    assert np.allclose(w, want, atol=1e-6) and abs(b - bias) < 1e-6


def test_near_dedup_goes_by_fingerprints(spark):
    """Without any band, near copies whose SimHash differs in at most three bits are linked; others that share it aren't."""
    from bicommunity.llm import resemblance, simhash
    from bicommunity.llm.store import Scratch

    long = [f"w{i}" for i in range(3000)]
    texts = [" ".join(long), " ".join(long[:-1] + ["end"]), " ".join(long[::-1])]
    fps = [simhash.fingerprint(t.encode(), 5) for t in texts]
    assert (fps[0] ^ fps[1]).bit_count() <= 3 < (fps[0] ^ fps[2]).bit_count()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    rows = resemblance.signatures(docs)
    assert {r.doc_id: r.fp % (1 << 64) for r in rows.collect()} == dict(enumerate(fps))
    nodes = rows.select("node", "n", F.col("doc_id").alias("first"), F.array("fp").alias("fps"), F.array().cast("array<long>").alias("buckets"))
    node = {r.first: r.node for r in nodes.collect()}
    got = resemblance.links(nodes, docs, Scratch(spark, "t")).collect()
    assert [{r.a, r.b} for r in got] == [{node[0], node[1]}]
    pairs = spark.createDataFrame([(1, 9, [0, 255]), (2, 9, [7]), (3, 9, [7, 1 << 40])], "node long, n long, fps array<long>")
    got = resemblance.by_fingerprint(pairs, Scratch(spark, "t")).select("a", "b").distinct().collect()
    assert sorted(map(tuple, got)) == [(1, 2), (1, 3), (2, 3)]
