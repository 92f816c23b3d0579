"""Near-duplicates, vectors, language, quality and the pipeline."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stepwalk.llm.components import components
from stepwalk.llm.hnsw import Graph
from stepwalk.llm.op4_embeddings import meet, near_vectors
from stepwalk.llm.op6_minhash import bags, near_duplicates, shingles, signatures
from stepwalk.llm.op7_language import Parser, automaton, identify, learn
from stepwalk.llm.op9_quality import AttentionScorer, classify, op9_quality, train
from stepwalk.llm.tables import table
from stepwalk.llm.textbatch import chunks

from .brute import bag
from .brute import near_duplicates as plain_duplicates


def test_components_of_paths_and_stars(spark):
    links = [(i, i + 1) for i in range(30)] + [(100, 100 + i) for i in range(1, 40)] + [(7, 7), (200, 201), (200, 201)]
    got = {r.node: r.root for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(31)) and all(got[100 + i] == 100 for i in range(40)) and got[201] == 200
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def edited(r, words, edits):
    words = list(words)
    for _ in range(edits):
        words[int(r.integers(0, len(words)))] = f"e{r.integers(0, 10**6)}"
    return " ".join(words)


def test_near_duplicates_match_plain(spark):
    r = np.random.default_rng(5)
    rows = [(i, " ".join(f"w{r.integers(0, 3000)}" for _ in range(int(r.integers(1, 80))))) for i in range(60)]
    base = [f"b{i}" for i in range(150)]
    rows += [(100 + i, edited(r, base, int(r.integers(0, 12)))) for i in range(120)]
    rows += [(300, None), (301, ""), (302, "one two"), (303, "one two"), (304, "ha " * 200), (305, "ha " * 190), (306, rows[3][1]), (3, rows[3][1])]
    frame = spark.createDataFrame([(i, t, 1.0) for i, t in rows], "doc_id long, text string, similarity double")
    want = plain_duplicates(list(dict(rows).items()))
    got = near_duplicates(frame).collect()
    assert len(got) == len(rows)
    assert {x.doc_id: (x.class_id, x.component_id) for x in got} == {**want, 300: got_of(got, 300), 301: got_of(got, 301)}
    assert got_of(got, 300) == (300, 300) and got_of(got, 301) == (301, 301)
    assert all(x.kept == (x.doc_id == x.component_id) for x in got)
    assert near_duplicates(frame.limit(0)).count() == 0


def got_of(rows, i):
    return next((x.class_id, x.component_id) for x in rows if x.doc_id == i)


def test_near_duplicates_with_null_and_clashing_ids(spark):
    r = np.random.default_rng(11)
    bases = [[f"c{k}_{i}" for i in range(120)] for k in range(25)]
    texts = [edited(r, bases[k % 25], int(r.integers(0, 4))) for k in range(150)] + [f"alone {i} " * 3 for i in range(10)] + [None, "", None]
    ids = [None if r.random() < 0.3 else int(r.integers(0, 60)) for _ in texts]
    ids += [None, None, 5]
    texts += ["a b c d e f g", "a b c d  e f g", "z y x w v u"]
    alone = plain_duplicates(list(enumerate(texts)))
    groups = {}
    for k, (_, component) in alone.items():
        groups.setdefault(component, []).append(k)
    frame = spark.createDataFrame(list(zip(ids, texts, strict=True)), "doc_id long, text string").repartition(3)
    got = near_duplicates(frame).join(frame.select("text", F.xxhash64("text").alias("text_key")).distinct(), "text_key").collect()
    assert len(got) == len(texts)
    found = {}
    for x in got:
        found.setdefault((x.doc_id, x.text), []).append(x)
    for own in groups.values():
        named = [ids[k] for k in own if ids[k] is not None]
        verdicts = [x for k in own for x in found[ids[k], texts[k]]]
        if texts[own[0]] and texts[own[0]].strip():
            assert len({x.component_id for x in verdicts}) == 1
            assert verdicts[0].component_id == min(named) if named else verdicts[0].component_id < 0
            assert len({(x.doc_id, x.text) for x in verdicts if x.kept}) == 1
        else:
            assert all(x.kept for x in verdicts)
    one = corpus_pipeline.near_copies(spark, frame, "")
    worded = sum(bool(texts[own[0]] and texts[own[0]].strip()) for own in groups.values())
    assert one.where("trim(text) <> ''").count() == worded and one.columns == ["doc_id", "text"]


def test_a_hot_centre_is_salted(spark, monkeypatch):
    from stepwalk.llm import op6_minhash

    r = np.random.default_rng(12)
    base = [f"b{i}" for i in range(200)]
    rows = [(i, edited(r, base, int(r.integers(0, 9)))) for i in range(200)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(op6_minhash, "MOST_PER_SALT", 7)
    assert {x.doc_id: (x.class_id, x.component_id) for x in near_duplicates(frame).collect()} == plain_duplicates(rows)


def test_signatures_estimate_weighted_similarity():
    import pyarrow as pa

    a, b = "x y z " * 30 + "p q r s t u v " * 4, "x y z " * 22 + "p q r s t u v " * 5
    chunk = next(iter(chunks([pa.record_batch({"text": pa.array([a, b])})])))
    rows, hashes, counts = bags(*shingles(chunk.words()))
    sig = signatures(rows, hashes, counts, 2, 4096)
    x, y = bag(a), bag(b)
    both = sum(min(n, y[k]) for k, n in x.items())
    want = both / (sum(x.values()) + sum(y.values()) - both)
    assert abs((sig[0] == sig[1]).mean() - want) < 0.04
    assert np.isfinite(sig).all()


def test_signatures_do_not_depend_on_the_batch():
    import pyarrow as pa

    r = np.random.default_rng(9)
    texts = [" ".join(f"w{r.integers(0, 50)}" for _ in range(int(r.integers(1, 300)))) for _ in range(200)]

    def of(some):
        chunk = next(iter(chunks([pa.record_batch({"text": pa.array(some)})])))
        return signatures(*bags(*shingles(chunk.words())), len(some))

    every = of(texts)
    for k in (0, 7, 199):
        assert (of([texts[k]])[0] == every[k]).all()


def clustered(r, n, d=24):
    centres = r.normal(size=(12, d))
    x = np.concatenate([centres[r.integers(0, 12, n // 2)] + 0.12 * r.normal(size=(n // 2, d)), r.normal(size=(n - n // 2, d))])
    return x[r.permutation(n)]


def test_graph_search_finds_links():
    r = np.random.default_rng(3)
    x = clustered(r, 1500)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    graph = Graph(unit.astype(np.float32), np.arange(1500))
    truth = unit @ unit.T >= 0.93
    np.fill_diagonal(truth, False)
    ones = np.ones(1500, np.int64)
    links, (width, audited, true, found) = meet(graph, np.arange(1500), ones, unit, np.arange(1500), ones, unit, 0.93, 0.99, True)
    assert (links.count[:1500] <= truth.sum(1)).all() and links.count[:1500].sum() / truth.sum() >= 0.99 and width < 1500
    assert audited >= 64 and true >= found >= 0.99 * true > 0


def test_rare_links_are_audited():
    r = np.random.default_rng(13)
    x = r.normal(size=(2000, 24))
    x[1777] = x[40] + 0.01 * r.normal(size=24)
    x[1200] = x[41] + 0.01 * r.normal(size=24)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    graph, ones = Graph(unit.astype(np.float32), np.arange(2000)), np.ones(2000, np.int64)
    links, (_, audited, true, found) = meet(graph, np.arange(2000), ones, unit, np.arange(2000), ones, unit, 0.93, 0.99, True)
    assert true > 0 and found >= 0.99 * true and audited > 0
    assert sorted(np.flatnonzero(links.count[:2000])) == [40, 41, 1200, 1777] and links.least()[1777] == 40


def test_vectors_of_any_magnitude(spark):
    rows = [(1, [1.0, 2.0, 3.0], 0), (2, [1e200, 2e200, 3e200], 0), (3, [1e-200, 2e-200, 3e-200], 0), (4, [1e308, 0.0, 0.0], 0), (5, [5e-324, 0.0, 0.0], 0), (6, [-1.0, -2.0, -3.0], 0)]
    audits = []
    got = {x.vec_id: (x.n_links, x.component_id) for x in near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int"), audits=audits).collect()}
    assert got == {1: (2, 1), 2: (2, 1), 3: (2, 1), 4: (1, 4), 5: (1, 4), 6: (0, 6)}
    told = audits[0].first()
    assert told.audited == 6 and told.found_links == told.true_links == 8 and told.recall == 1.0


def test_near_vectors_match_plain(spark):
    r = np.random.default_rng(4)
    x = clustered(r, 300).round(3)
    rows = [(i, [float(v) for v in x[i]], int(i % 2)) for i in range(300)]
    rows += [(400 + k, rows[0][1], 0) for k in range(5)] + [(500, None, 0), (501, [0.0] * 24, 0), (502, [float("nan")] + [1.0] * 23, 0), (503, [None] + [1.0] * 23, 0), (504, rows[0][1], None), (505, rows[0][1][:10], 0), (None, rows[0][1], 0), (506, [], 1)]
    frame = spark.createDataFrame([(*v, "k") for v in rows], "vec_id long, embedding array<double>, label int, links string")
    usable = [v for v in rows if v[0] is not None and v[1] and v[2] is not None and all(c is not None and np.isfinite(c) for c in v[1]) and any(v[1])]
    near = {v[0]: set() for v in rows}
    for a in usable:
        for b in usable:
            if a[0] != b[0] and a[2] == b[2] and len(a[1]) == len(b[1]) and np.dot(a[1], b[1]) / np.linalg.norm(a[1]) / np.linalg.norm(b[1]) >= 0.93:
                near[a[0]].add(b[0])
    low = {v: v for v in near}
    for _ in range(20):
        low = {v: min([low[v], *(low[u] for u in near[v])]) if near[v] else v for v in near}
    for size in (64, 8192):
        got = near_vectors(frame, shard_size=size).collect()
        assert len(got) == len(rows)
        assert {g.vec_id: (g.n_links, g.component_id) for g in got} == {v: (len(near[v]), low[v]) for v in near}
    assert near_vectors(frame.limit(0)).count() == 0


def test_automaton_holds_exactly_the_factors():
    text = [1, 2, 1, 1, 2, 3]
    follow, _ = automaton(text)

    def held(s):
        state = 0
        for c in s:
            if c not in follow[state]:
                return False
            state = follow[state][c]
        return True

    factors = {tuple(text[i:j]) for i in range(6) for j in range(i + 1, 7)}
    for a in range(1, 4):
        for b in range(1, 4):
            for c in range(1, 4):
                assert held((a, b, c)) == ((a, b, c) in factors)


def test_lockstep_phrases_match_plain():
    samples = {"x": b"the cat sat on the mat and the dog", "y": b"der hund und die katze"}
    p = Parser(samples)
    text = b"the mat and hund die"

    def plain(sample):
        sample, n, i = sample.decode(), 0, 0
        t = text.decode()
        while i < len(t):
            k = 1
            while i + k < len(t) and t[i : i + k + 1] in sample:
                k += 1
            n, i = n + 1, i + k
        return n

    rates = p.rates(np.frombuffer(text, np.uint8), np.array([0, len(text)]))[0]
    want = [plain(samples[k]) * p.log_size[j] / len(text) for j, k in enumerate(p.names)]
    np.testing.assert_allclose(rates, want)


def plain_phrases(text, sample):
    n = i = 0
    while i < len(text):
        k = 1
        while i + k < len(text) and text[i : i + k + 1] in sample:
            k += 1
        n, i = n + 1, i + k
    return n


def test_whole_texts_are_parsed_in_one():
    r = np.random.default_rng(2)
    word = lambda: "".join(r.choice(list("aabcde"), int(r.integers(1, 7))))
    known = [word() for _ in range(60)]
    prose = lambda n: " ".join(r.choice(known, n))
    samples = {"x": prose(900), "y": " ".join(word() for _ in range(700)), "z": "ha" * 40}
    texts = [samples["x"], samples["x"][100:2400] + prose(600) + samples["y"], "ha" * 2600, "a" * 5000, "qq" * 1500, "ab " + samples["y"] * 2, prose(1200), "", "a", prose(90)[:512], prose(200)[:513], prose(400)[:1024], "ha" * 300 + samples["x"] + "ha" * 700]
    texts += [prose(int(r.integers(1, 1500))) for _ in range(12)]
    data = [t.encode() for t in texts]
    p = Parser({k: v.encode() for k, v in samples.items()})
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in data])])
    rates = p.rates(np.frombuffer(b"".join(data), np.uint8), offsets)
    for k, t in enumerate(texts):
        if t:
            want = [plain_phrases(t, samples[n]) for n in p.names]
            np.testing.assert_allclose(rates[k] * len(t) / p.log_size, want, err_msg=t[:50])
    assert plain_phrases(texts[0], samples["x"]) == 1 and len(texts[0]) > 3000


def test_language_held_out_and_edges(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    from stepwalk.llm.op7_language import op7_language

    found = op7_language(spark, "/root/testdata/sf0.01").join(docs, "doc_id")
    r = found.where("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int")).alias("a"), F.min("score").alias("low"), F.max("score").alias("high")).first()
    assert r.a > 0.97 and 0 <= r.low and r.high <= 1
    samples = learn(docs.select("doc_id", "text", "lang"))
    rows = spark.createDataFrame([(1, None, "a"), (2, "", "b"), (3, "123 !!", "c"), (4, "é", "d"), (5, "☃", "e"), (None, "the and of", "f")], "doc_id long, text string, lang_pred string")
    got = {x.doc_id: x for x in identify(rows, samples).collect()}
    assert [got[i].lang_pred for i in (1, 2, 3, 5)] == ["und"] * 4 and got[1].score == 0
    assert got[4].lang_pred in samples and got[None].lang_pred == "en"
    assert identify(rows.limit(0), samples).count() == 0
    assert identify(rows, {}).select("lang_pred").distinct().collect() == [("und",)]
    assert learn(docs.limit(0).select("doc_id", "text", "lang")) == {}


def test_quality_held_out_and_edges(spark):
    sf = "/root/testdata/sf0.01"
    found = op9_quality(spark, sf).join(table(spark, sf, "labels"), "doc_id").where("held_out")
    assert found.agg(F.avg((F.col("quality") == F.col("predicted")).cast("int"))).first()[0] > 0.95
    hard = spark.createDataFrame([(1, None, 0.0), (2, "", 0.0), (3, "a", 0.0), (None, "b c", 0.0), (4, "x " * 5000, 0.0)], "doc_id long, text string, score double")
    scorer = train(table(spark, sf, "documents"), table(spark, sf, "labels"), per_label=50)
    got = classify(hard, scorer)
    assert got.count() == 5 and got.where("score < 0 OR score > 1 OR score IS NULL").count() == 0
    assert classify(hard.limit(0), scorer).count() == 0
    none = train(table(spark, sf, "documents"), table(spark, sf, "labels").limit(0))
    assert classify(hard, none).select("score").distinct().collect() == [(0.5,)]


def test_quality_learns_from_a_bounded_sample(spark, monkeypatch):
    from stepwalk.llm import op9_quality

    seen = []
    fit = AttentionScorer.fit
    monkeypatch.setattr(op9_quality.AttentionScorer, "fit", lambda self, x, per, label: seen.append((x, per, label)) or fit(self, x, per, label))
    rows = [(7, f"repeated id {i} " * 40) for i in range(500)] + [(i, f"good words number {i} " * 30) for i in range(100, 140)] + [(9, "long " * 20_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(r[0], r[0] % 2) for r in rows] + [(7, 1), (None, 1)], "doc_id long, quality int")
    train(docs, labels, most_passages=200)
    x, per, label = seen[0]
    assert len(per) == 41 and per.sum() == len(x) <= 200 and len(label) == 41
    train(docs, labels, most_passages=1000)
    assert len(seen[1][1]) == 42 and seen[1][1].max() == -(-20_000 // 64)


def plain_score(s, text):
    """The forward pass of one text, passage by passage."""
    import re
    from collections import Counter

    words = [(m.start(), m.group()) for m in re.finditer(r"[^\x20\x09-\x0D]+", text)]
    cuts = [0] + [words[k][0] for k in range(64, len(words), 64)] + [len(text)]
    three = Counter(tuple(w for _, w in words[k : k + 3]) for k in range(len(words) - 2))
    covered = {k + j for k in range(len(words) - 2) if three[tuple(w for _, w in words[k : k + 3])] > 1 for j in range(3)}
    marks = [b for b in range(33, 127) if not chr(b).isalnum()]
    bags = []
    for n, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)):
        own = [w for _, w in words[64 * n : 64 * n + 64]]
        part, x = text[a:b], np.zeros(7 + len(marks) + 6)
        for c in part:
            k = 0 if c.islower() else 1 if c.isupper() else 2 if c.isdigit() else 3 if c == " " else 4 if c == "\n" else 7 + marks.index(ord(c)) if ord(c) in marks else 5
            x[k] += 1 / max(1, len(part))
        m = max(1, len(own))
        again = sum(words[k][1] == words[k - 1][1] for k in range(64 * n, 64 * n + len(own)) if k)
        x[-6:] = sum(map(len, own)) / m / 10, again / m, len(set(own)) / m, sum(64 * n <= k < 64 * n + 64 for k in covered) / m, len(own) / 64, np.log1p(len(words)) / 10
        bags.append(x)
    p = s.p
    h = [np.tanh(np.clip((x - s.mean) / s.scale, -8, 8) @ p["encode"] + p["shift"]) for x in bags]
    e = np.array([(np.tanh(v @ p["v"]) / (1 + np.exp(-(v @ p["u"])))) @ p["w"] for v in h])
    a = np.exp(e) / np.exp(e).sum()
    return 1 / (1 + np.exp(-(sum(k * v for k, v in zip(a, h, strict=True)) @ p["score"] + p["bias"][0])))


def test_quality_scores_match_plain(spark):
    r = np.random.default_rng(6)
    scorer = AttentionScorer()
    scorer.constant, scorer.mean, scorer.scale = None, r.normal(size=scorer.mean.shape) * 0.1, 0.5 + r.random(scorer.scale.shape)
    words = ["One", "two,", "three", "x", "x", "4.5", "(six)", "#7", "eight\n"]
    texts = ["", "a", "x x x x"] + [" ".join(r.choice(words, int(r.integers(1, 400)))) for _ in range(15)]
    got = {x.doc_id: x.score for x in classify(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), scorer).collect()}
    np.testing.assert_allclose([got[k] for k in range(len(texts))], [plain_score(scorer, t) for t in texts], rtol=1e-6)


def test_attention_gradients():
    r = np.random.default_rng(1)
    s = AttentionScorer(6, 5, 4)
    x, per, y = r.normal(size=(9, 6)), np.array([2, 4, 3]), np.array([1.0, 0.0, 1.0])
    grads = s.gradients(x, per, y)

    def loss():
        p = s.forward(x, per)["y"]
        return -(y * np.log(p) + (1 - y) * np.log(1 - p)).mean()

    for name, g in grads.items():
        at = tuple(0 for _ in g.shape)
        keep = s.p[name][at]
        s.p[name][at] = keep + 1e-6
        up = loss()
        s.p[name][at] = keep - 1e-6
        down = loss()
        s.p[name][at] = keep
        assert g[at] == pytest.approx((up - down) / 2e-6, abs=1e-6)


def test_pipeline_stages_act(spark, sf):
    docs = table(spark, sf, "documents")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, sf)
        assert after.columns == docs.columns, name
        assert after.select("doc_id").distinct().count() == after.count() <= before.count()
        before = spark.createDataFrame(after.toArrow())
    packed = corpus_pipeline.run(spark, sf)
    assert packed.select("doc_id").distinct().count() == before.count()
    texts = [(r.doc_id, r.text) for r in before.collect()]
    labels = {r.doc_id: r.quality for r in table(spark, sf, "labels").collect()}
    kept = {i for i, _ in texts}
    bad = [i for i, q in labels.items() if q == 0]
    assert sum(i in kept for i in bad) <= 0.1 * len(bad)


def test_pipeline_stages_keep_clashing_columns_and_null_ids(spark, sf):
    docs = table(spark, sf, "documents")
    extra = {"score": F.lit("own"), "predicted": F.lit("p"), "lang_pred": F.lit(7), "n_words": F.lit("n"), "kept_text": F.lit("k"), "class_id": F.lit("c"), "text_key": F.lit("t"), "key": F.lit("y"), "node": F.lit("z")}
    wide = docs.withColumn("doc_id", F.when(F.col("doc_id") % 5 > 0, F.col("doc_id"))).withColumns(extra)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, wide, sf)
        assert after.columns == wide.columns and after.schema["lang_pred"].dataType.typeName() == "integer", name
        got = after.select(*extra).distinct().collect()
        assert [tuple(x) for x in got] == [("own", "p", 7, "n", "k", "c", "t", "y", "z")], name
        assert 0 < after.count() <= wide.count()
        wide = spark.createDataFrame(after.toArrow())
    assert wide.where("doc_id is null").count() > 0
    assert corpus_pipeline.STAGES[-1][1](spark, wide, sf).count() > 0


def test_pipeline_stages_take_nothing(spark, sf):
    none = table(spark, sf, "documents").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, sf).count() == 0


def test_pipeline_language_rejects_by_the_parse(spark, sf):
    docs = table(spark, sf, "documents")
    r = np.random.default_rng(8)
    junk = [" ".join("".join(r.choice(list("abcdefghijklmnopqrstuvwxyz"), int(r.integers(2, 12)))) for _ in range(60)) for _ in range(5)]
    junk += ["Это предложение написано на другом языке и не должно остаться. " * 3, "這句話是用另一種語言寫的。" * 5, "12 34 -- !!", None]
    more = spark.createDataFrame([(10_000 + i, t, None, None, 0) for i, t in enumerate(junk)], docs.schema)
    kept = {x.doc_id for x in corpus_pipeline.language(spark, docs.unionByName(more), sf).select("doc_id").collect()}
    worded = {x.doc_id for x in docs.where("text rlike '[A-Za-z]'").collect()}
    assert kept == worded


def test_every_labelled_language_is_learned(spark):
    import corpus_pipeline

    long = {"aa": "abra kadabra " * 2000, "bb": "日本語 の テキスト " * 900}
    rows = [(i, t, k) for k, t in long.items() for i in range(40)] + [(None, "same row", "cc")] * 2000
    rows += [(i, f"tongue number {i}", f"x{i}") for i in range(300)]
    labelled = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    samples = learn(labelled)
    assert set(samples) == {r[2] for r in rows} and max(map(len, samples.values())) <= 60_000 + 150
    assert min(len(samples[k]) for k in long) > 12_000 and samples["x7"] == b"tongue number 7"
    assert learn(labelled.where("lang = 'bb' and doc_id = 1"))["bb"].decode() in long["bb"]
    two = learn(labelled.where("lang in ('aa', 'bb')"))
    assert min(map(len, two.values())) > 50_000 and two == learn(labelled.where("lang in ('aa', 'bb')").repartition(3))
    some = {k: samples[k] for k in (*long, "cc")}
    got = identify(labelled.where("lang in ('aa', 'bb')"), some).where("lang <> lang_pred").count()
    assert got == 0
    unlabelled = spark.createDataFrame([(1, "some words", None), (2, "1 2", None)], labelled.schema)
    assert corpus_pipeline.language(spark, unlabelled, "").count() == 2
