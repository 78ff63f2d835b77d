"""Operators on whole corpora against brute force on small tables."""

import hashlib
import random
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from couponspark.llm import common as C
from couponspark.llm import components as CC
from couponspark.llm import pseudo_lm as L
from couponspark.llm import quality_rules as QR
from couponspark.llm import queries
from couponspark.llm import set_join as J
from couponspark.llm import suffix_dedup as X
from couponspark.llm import toxicity as T
from couponspark.llm import vector_dedup as V


def cut_by_force(docs, n=50):
    """(doc_id, text) in order of id: spans and kept bytes of each."""
    seen, out = {}, []
    for d, x in sorted(docs):
        for j in range(len(x) - n + 1):
            seen.setdefault(x[j : j + n], d)
    for d, x in docs:
        cover = bytearray(len(x))
        for j in range(len(x) - n + 1):
            if seen[x[j : j + n]] < d:
                cover[j : j + n] = b"\1" * n
        kept = bytes(c for c, v in zip(x, cover, strict=True) if not v)
        out.append((d, len(x), sum(cover), len([r for r in bytes(cover).split(b"\0") if r]), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def digest(df):
    return sorted(tuple(r) for r in df.collect())


def test_suffix_query(spark):
    d = "/root/testdata/sf0.001"
    docs = [(r.doc_id, r.text.encode()) for r in spark.read.parquet(f"{d}/documents.parquet").collect()]
    assert digest(queries.op1_suffix_dedup(spark, d)) == cut_by_force(docs)


def test_suffix_edges(spark):
    rng = random.Random(2)
    word = lambda n: "".join(rng.choice("abcdefgh ") for _ in range(n))
    passage, lead = word(120), word(60)
    rows = [(i, word(40) + passage + word(30)) for i in range(40)]
    rows += [(50, "a" * 400), (51, "a" * 90 + "b"), (52, "é" * 60 + passage[:70]), (53, "é" * 60), (54, ""), (55, passage[:49]), (56, lead), (57, lead), (57, lead), (58, "x" + passage[10:61])]
    docs = [(d, x.encode()) for d, x in rows]
    df = spark.createDataFrame([(d, x, 7) for d, x in rows] + [(60, None, 1), (None, lead, 1)], "doc_id long, text string, block int")
    got = X.suffix_dedup(df).collect()
    assert sorted(tuple(r) for r in got if r.doc_id not in (60, None)) == cut_by_force(docs)
    odd = {r.doc_id: r for r in got if r.doc_id in (60, None)}
    assert odd[60].n_bytes == 0 and odd[None].n_removed == 0
    assert X.suffix_dedup(df.where("false")).count() == 0
    text = X.suffix_dedup(df, mode="text")
    assert text.columns == ["doc_id", "text", "block"]
    kept = {r.doc_id: r.text for r in text.collect()}
    assert passage not in kept[30] and kept[0] == rows[0][1] and kept[60] is None and kept[57] == ""


def test_suffix_repeated_ids(spark):
    """A row whose id also names a copy of another text keeps its own."""
    rng = random.Random(5)
    a, b, c = ("".join(rng.choice("abcdefgh ") for _ in range(200)) for _ in range(3))
    rows = [(1, a), (5, a), (5, b), (5, "x" + b[20:120] + c), (6, b), (6, c), (6, c), (9, a + c)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    seen = [(d, x.encode()) for d, x in rows]
    assert digest(X.suffix_dedup(df)) == cut_by_force(seen)
    kept = sorted((r.doc_id, r.text) for r in X.suffix_dedup(df, mode="text").collect())
    assert (5, b) in kept and (1, a) in kept and (5, "") in kept and (6, "") in kept


def test_suffix_hash_zero(spark, monkeypatch):
    """Grams whose hash ends in 32 zero bits are anchors like all others."""

    class Zero:
        prefixes = staticmethod(X.HASH.prefixes)

        @staticmethod
        def windows(prefix, size):
            h = real.windows(prefix, size)
            return np.where(h % np.uint64(8) == 0, h & ~np.uint64(0xFFFFFFFF), h)

    real = X.HASH
    buf = np.frombuffer(bytes(random.Random(1).choices(b"abcdef", k=300)), np.uint8)
    monkeypatch.setattr(X, "HASH", Zero)
    at, _ = X.anchors(buf, np.zeros(1, np.int64), 50)
    covered = np.zeros(251, bool)
    for p in at:
        covered[max(0, p - 26) : p + 1] = True
    assert covered.all()


def test_cuts_leave_a_gap(spark):
    rng = random.Random(6)
    passage = "".join(rng.choice("ghijklm ") for _ in range(100))
    rows = [(1, "-" + passage + "-"), (2, "0123456789abcdef" + passage + "0123456789abcdef"), (3, passage[:80])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    kept = {r.doc_id: r.text for r in X.suffix_dedup(df, mode="text").collect()}
    assert kept == {1: rows[0][1], 2: "0123456789abcdef\n0123456789abcdef", 3: ""}


def test_loser_tree():
    rng = np.random.default_rng(4)
    for n in (1, 2, 5, 9):
        runs, flat = [], []
        for _ in range(n):
            rows = np.unique(rng.integers(97, 99, (rng.integers(0, 40), 8), dtype=np.uint8), axis=0)
            lcp, rest = X.front_code(rows)
            assert (X.front_decode(lcp, rest, 8) == rows).all()
            words = [int.from_bytes(r.tobytes(), "big") for r in rows]
            runs.append((words, lcp.tolist()))
            flat += words
        order, lcps = X.merge_runs(runs, 8)
        place = [0] * n
        merged = []
        for r in order:
            merged.append(runs[r][0][place[r]])
            place[r] += 1
        assert merged == sorted(flat)
        for a, b, l in zip(merged, merged[1:], lcps[1:], strict=False):
            assert l == (64 - (a ^ b).bit_length()) // 8


def brute_components(docs, percent=75):
    sets = {}
    for d, x in docs:
        w = (x or "").encode().lower().split()
        sets[d] = {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}
    forest, ids = CC.Forest(), sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            n = len(sets[a] & sets[b])
            if n and 100 * n >= percent * len(sets[a] | sets[b]):
                forest.join(a, b)
    return {d: (len(sets[d]), forest.root(d)) for d in ids}


def perturbed(rng, base, changes):
    w = list(base)
    for _ in range(changes):
        w[rng.randrange(len(w))] = f"n{rng.randrange(10**6)}"
    return " ".join(w)


@pytest.mark.parametrize("small", [False, True])
def test_set_join(spark, monkeypatch, small):
    if small:  # large nodes, deep trees and pivots on few rows
        for name, value in (("LEAF", 4), ("CHUNK", 6)):
            monkeypatch.setattr(J, name, value)
        monkeypatch.setattr(J.candidate_links, "__defaults__", (4, J.RECALL, J.DEPTH))
    rng = random.Random(7)
    rows, n = [], 0
    for g in range(6):
        base = [f"w{rng.randrange(10**5)}" for _ in range(60)]
        for _ in range(25 if g == 0 else 4):
            rows.append((n, perturbed(rng, base, rng.choice([0, 1, 1, 2, 3, 5]))))
            n += 1
    rows += [(n, "One two"), (n + 1, "one  TWO"), (n + 2, ""), (n + 3, " \n "), (n + 4, "alone here now and then again")]
    want = brute_components(rows)
    df = spark.createDataFrame([(d, x, 1) for d, x in rows] + [(n + 5, None, 1), (None, rows[0][1], 1)], "doc_id long, text string, rep int")
    got = {r.doc_id: r for r in J.near_duplicates(df).collect()}
    assert {d: (r.n_shingles, r.component_id) for d, r in got.items() if d in want} == want
    assert all(r.kept == (r.doc_id == r.component_id) for d, r in got.items() if d is not None)
    assert got[n + 5].n_shingles == 0 and got[None].kept and got[None].component_id is None
    left = {r.doc_id for r in J.drop_near_duplicates(df).collect()}
    assert left == {d for d, (_, c) in want.items() if d == c} | {n + 5, None}
    assert J.near_duplicates(df.where("false")).count() == 0


def test_set_join_recall(spark, monkeypatch):
    """Pairs right above the threshold among many documents that share much: found at the recall asked for, and no other is linked."""
    monkeypatch.setattr(J.candidate_links, "__defaults__", (8, J.RECALL, J.DEPTH))  # all stay in large nodes
    rng = random.Random(11)
    common = [f"c{i}" for i in range(60)]
    rows = []
    for g in range(300):
        own = [f"w{g}x{i}" for i in range(100)]
        other = list(own)
        at = rng.randrange(40, 60)
        other[at : at + 16] = [f"z{g}x{i}" for i in range(16)]  # 156 shingles each, 136 shared: similarity 0.773
        rows += [(2 * g, " ".join(common + own)), (2 * g + 1, " ".join(common + other))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(8)
    got = {r.doc_id: r.component_id for r in J.near_duplicates(df).collect()}
    assert all(c in (d, d - 1) for d, c in got.items())
    assert sum(got[2 * g + 1] == 2 * g for g in range(300)) >= 0.97 * 300
    assert J.recall_of(J.trees_for(0.99, 0.75), 0.75) >= 0.99 > J.recall_of(J.trees_for(0.99, 0.75) - 1, 0.75)
    assert J.trees_for(0.9, 0.75) < J.trees_for(J.RECALL, 0.75)


def test_set_join_repeated_ids(spark):
    a, b = ([f"{x}{i}" for i in range(40)] for x in "ab")
    rows = [(1, " ".join(a)), (5, " ".join(a)), (5, " ".join(b)), (5, ""), (7, " ".join(b)), (8, "one two"), (9, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in J.near_duplicates(df).collect())
    assert got == [(1, 36, 1, True), (5, 0, 5, True), (5, 36, 1, False), (5, 36, 1, False), (7, 36, 1, False), (8, 1, 8, True), (9, 0, 9, True)]
    assert sorted(r.doc_id for r in J.drop_near_duplicates(df.withColumn("__gone", df.doc_id)).collect()) == [1, 8, 9]


def test_components(spark):
    n = 400
    links = [(i, i + 1) for i in range(n)] + [(1000 + i, 1000) for i in range(1, 50)] + [(5, None), (7, 7)]
    df = spark.createDataFrame(links, "a long, b long").repartition(5)
    for bound in (10, 10**6):
        got = {r.id: r.component for r in CC.components(df, bound).collect()}
        assert all(got[i] == 0 for i in range(1, n + 1)) and all(got[1000 + i] == 1000 for i in range(1, 50))


@pytest.mark.parametrize("hot", [2, 4096])
def test_joins_hold_nothing_in_the_driver(spark, monkeypatch, hot):
    """However small Spark takes a side to be, it is not broadcast; keys of many rows, of few and of none meet their one row."""
    monkeypatch.setattr(C, "HOT", hot)
    many = spark.createDataFrame([(i, i % 7 if i < 60 else 7 + i % 2) for i in range(100)] + [(100, 50), (101, None)], "id long, key long")
    one = many.where("key is not null and key <> 50").groupBy("key").agg(F.count("*").alias("n"))
    one = C.stage(one.where("n > 1"), "one")
    for how in ("inner", "left"):
        for joined in (C.dealt_join(many, one, ["key"], "id", "n", how), C.salted_join(many, one, ["key"], "id", how)):
            assert "Broadcast" not in joined._jdf.queryExecution().sparkPlan().toString()
            got = sorted((r.id, r.key, r.n) for r in joined.select("id", "key", "n").collect())
            assert got == sorted((r.id, r.key, r.n) for r in many.join(one, "key", how).collect())


def test_pairs_hold_nothing_in_the_driver(spark, monkeypatch):
    """No join that a query of pairs runs is broadcast, but for labels whose number is bounded."""
    rng, seen, stage = np.random.default_rng(4), [], C.stage

    def watched(df, name):
        seen.append((name, df._jdf.queryExecution().sparkPlan().toString()))
        return stage(df, name)

    for module in (V, J, CC):
        monkeypatch.setattr(module, "stage", watched)
    x = rng.standard_normal((40, 8))
    vectors = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(np.r_[x, x[:10] + 0.01])], "vec_id long, embedding array<float>")
    docs = spark.createDataFrame([(i, " ".join(f"w{i % 20}x{j}" for j in range(30))) for i in range(50)], "doc_id long, text string")
    for df in (V.near_vectors(vectors), J.near_duplicates(docs), J.drop_near_duplicates(docs)):
        seen.append(("result", df._jdf.queryExecution().sparkPlan().toString()))
    assert len(seen) > 10 and [name for name, text in seen if "Broadcast" in text] == []


def test_vectors(spark, monkeypatch):
    monkeypatch.setattr(V, "BLOCK", 16)
    rng = np.random.default_rng(1)
    base = rng.standard_normal((30, 16))
    x = np.concatenate([base, base[:8] + 0.05 * rng.standard_normal((8, 16)), np.repeat(base[:1], 60, axis=0) + 0.02 * rng.standard_normal((60, 16)), base[3:4], base[3:4] * 2])
    rows = [(i, v.tolist(), 1) for i, v in enumerate(x)]
    odd = [(500, None, 1), (501, [0.0] * 16, 1), (502, [1.0, None], 1), (503, [float("nan")] * 16, 1), (504, [], 1), (None, base[0].tolist(), 1), (505, [1.0, 2.0], 1)]
    df = spark.createDataFrame(rows + odd, "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: r for r in V.near_vectors(df).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = u @ u.T >= 0.9
    np.fill_diagonal(near, False)
    forest = CC.Forest()
    for i, j in zip(*np.nonzero(near), strict=True):
        forest.join(int(i), int(j))
    assert [got[i].n_links for i in range(len(x))] == near.sum(axis=1).tolist()
    assert [got[i].component_id for i in range(len(x))] == [forest.root(i) for i in range(len(x))]
    assert all(got[i].n_links == 0 and got[i].component_id == i for i in (500, 501, 502, 503, 504, 505))
    assert V.near_vectors(df.where("false")).count() == 0


def test_plan_grows_with_the_logarithm():
    _, k1, t1 = V.plan(10**3, 0.9, 0.99)
    _, k2, t2 = V.plan(10**9, 0.9, 0.99)
    assert k1 < k2 < 4 * k1 + 20 and t1 < t2 < 100
    assert V.collide(0.447, 1.79) > V.collide(1.41, 1.79)


def test_language_model(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = L.fit(docs)
    out = {r.doc_id: r for r in L.score(docs, model).collect()}
    n = sum(r.n_tokens for r in out.values())
    assert sum(r.log_probability for r in out.values()) / n > sum(r.unigram_log_probability for r in out.values()) / n + 0.15
    rng = random.Random(1)
    texts = [r.text for r in docs.limit(150).collect()]
    mixed = [" ".join(rng.sample(t.split(), len(t.split()))) for t in texts]
    both = spark.createDataFrame([(i, t) for i, t in enumerate(texts + mixed)], "doc_id long, text string")
    s = {r.doc_id: r.log_probability for r in L.score(both, model).collect()}
    assert np.mean([s[i] > s[i + 150] for i in range(150) if len(texts[i].split()) > 20]) > 0.9
    edge = spark.createDataFrame([(1, None, 1), (2, "", 1), (3, "one word", 1), (3, "one word", 1)], "doc_id long, text string, slice int")
    e = L.pseudo_likelihood(edge).collect()
    assert [(r.n_tokens, r.log_probability) for r in e if r.doc_id < 3] == [(0, 0.0), (0, 0.0)]
    assert L.pseudo_likelihood(edge.where("doc_id < 3")).count() == 2 and L.pseudo_likelihood(edge.where("false")).count() == 0


def test_language_model_free_of_layout(spark, monkeypatch):
    """The same scores from one partition and from many, in any order of rows; equal to a slow reference; long texts, ties and repeats."""
    monkeypatch.setattr(L, "SHARD", 1 << 16)
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    long = " ".join(r.text for r in docs.limit(20).collect()) * 4
    docs = docs.union(spark.createDataFrame([(10**6, long), (10**6 + 1, "tie tie"), (10**6 + 1, "tie tie"), (10**6 + 2, "tie tie")], "doc_id long, text string"))
    values = lambda rows: sorted((r.doc_id, r.n_tokens, r.log_probability, r.n_once) for r in rows)
    a, b = (values(L.pseudo_likelihood(d).collect()) for d in (docs.coalesce(1), docs.orderBy(F.rand(3)).repartition(13)))
    assert [x[:2] for x in a] == [x[:2] for x in b] and np.allclose([x[2] for x in a], [x[2] for x in b], rtol=1e-9) and [x[3] for x in a] == [x[3] for x in b]
    model = L.fit(docs)
    got = {r.doc_id: r.log_probability for r in L.score(docs, model).collect()}
    held, net, lex = {bytes(r.word): r.n for r in L.word_counts(model.held).collect()}, L.Net(model.flat), model.lexicon
    for row in docs.limit(5).collect():
        words = row.text.encode().split()[:10**6]
        array = pa.array(words, pa.large_binary())
        n = np.array([held[w] for w in words])
        context, klass, place = lex.context(array), lex.klass(array, n), lex.place(array, n)
        want = 0.0
        for i in range(len(words)):
            h = net.hide.astype(np.float64).copy()
            for k, d in enumerate(L.SIDES):
                h += net.side[k][context[i + d] if 0 <= i + d < len(words) else L.CONTEXTS]
            h = np.tanh(h)
            z = h @ net.out + net.bias
            want += z[klass[i]] - np.log(np.exp(z).sum())
            if L.OWN_CLASS <= klass[i] < L.OWN_CLASS + L.GROUPS:
                z = h @ net.inner[klass[i] - L.OWN_CLASS] + net.inner_bias[klass[i] - L.OWN_CLASS]
                want += z[place[i]] - np.log(np.exp(z).sum())
            elif klass[i] >= L.OWN_CLASS:
                want += np.log(n[i] / lex.total[klass[i]])
        assert got[row.doc_id] == pytest.approx(want, rel=1e-4)


def test_masked_words_do_not_see_themselves():
    ids, sizes = L.tokenize([b"a b c", b"d e"])
    around = L.windows(ids, sizes, np.arange(L.BUCKETS) % L.CONTEXTS)
    own = ids % L.CONTEXTS
    assert sizes.tolist() == [3, 2] and around[2][2] == L.CONTEXTS and around[1][3] == L.CONTEXTS
    assert around[1][1] == own[0] and around[2][1] == own[2]


def test_language_model_counts_words_exactly(spark):
    rng = random.Random(4)
    rows = [(i, " ".join(f"{'common' if j % 2 else 'plain'}{rng.randrange(40)}" if j % 4 else f"once{i}x{j}" for j in range(400))) for i in range(1500)]
    docs = spark.createDataFrame([*rows, (-1, "once0x0"), (-2, "common1"), (-3, "once7x4")], "doc_id long, text string")
    want = {}
    for _, text in [*rows, (-1, "once0x0"), (-2, "common1"), (-3, "once7x4")]:
        for w in text.split():
            want[w] = want.get(w, 0) + 1
    assert len(want) > 2 * L.BUCKETS
    got = {r.doc_id: r.unigram_log_probability for r in L.pseudo_likelihood(docs).collect()}
    total = sum(want.values())
    for d, w in ((-1, "once0x0"), (-2, "common1"), (-3, "once7x4")):
        assert got[d] == pytest.approx(np.log(want[w] / total), abs=1e-3), w
    model = L.fit(docs)
    assert {bytes(r.word).decode(): r.n for r in L.word_counts(model.held).collect()} == want


def test_toxicity_gradient():
    texts = [b"an idiot of the worst kind we see here today", b"good and clean words are all that is in here", b"short text"]
    net = T.Network()
    net.start(3)
    net.weights = {k: v.astype(np.float64) for k, v in net.weights.items()}
    net.word_odds, net.gram_odds = np.random.default_rng(0).standard_normal(T.WORDS), np.random.default_rng(1).standard_normal(T.GRAMS)
    words = [T.split_words(t) for t in texts]
    distinct, ids = T.number(words)
    v = T.Vocabulary.of(distinct)
    table = np.r_[ids, -1][T.window_table([len(w) for w in words])[0]]
    y, w = np.array([1.0, 0, 1]), np.ones(3)
    grad, _ = net.gradient(v, net.inputs(v).astype(float), table, y, w)
    for name, g in grad.items():
        flat, j = net.weights[name].ravel(), int(np.argmax(np.abs(g)))
        old, loss = flat[j], []
        for step in (1e-3, -1e-3):
            flat[j] = old + step
            loss.append(net.gradient(v, net.inputs(v).astype(float), table, y, w)[1])
        flat[j] = old
        assert (loss[0] - loss[1]) / 2e-3 == pytest.approx(g.ravel()[j], rel=2e-3, abs=1e-5), name


def test_windows_overlap_and_cover():
    for n in (0, 1, 31, 32, 33, 57, 500):
        table, owner = T.window_table([n])
        assert set(table[table >= 0].tolist()) == set(range(n)) and set(owner.tolist()) == {0}


def test_toxicity_query(spark):
    d = "/root/testdata/sf0.1"
    rows = {r.doc_id: r for r in queries.op10_toxicity(spark, d).collect()}
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    out = [(labels[i], rows[i]) for i in labels if rows[i].held_out]
    bad, good = [r for y, r in out if y == 1], [r for y, r in out if y == 0]
    assert np.mean([a.score > b.score for a in bad for b in good]) > 0.9
    hits = [y for y, r in out if r.predicted == 1]
    assert np.mean(hits) > 0.8 and sum(hits) > 0.5 * len(bad)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3) for r in rows.values())


def test_samples_stay_bounded(spark, monkeypatch):
    """An id that very many rows have, and labels that repeat or contradict each other, leave one row of each id to the fits."""
    ids = [i for i in range(1, 40) if zlib.crc32(str(i).encode()) % 4 != 2][:6]
    hot, both = ids[0], ids[1]
    docs = spark.createDataFrame([(hot, f"copy number {i} of a text") for i in range(3000)] + [(i, f"only text of {i}") for i in ids[1:]], "doc_id long, text string")
    labels = spark.createDataFrame([(hot, 0, 1)] * 3 + [(both, 0, 1), (both, 1, 0)] + [(i, 1, 0) for i in ids[2:]] + [(None, 1, 1)], "doc_id long, quality int, toxic int")
    got = sorted((r.doc_id, r.toxic) for r in T.training_rows(docs, labels).collect())
    assert got == [(hot, 1), (both, 1), *((i, 0) for i in ids[2:])]
    again = {r.text for d in (docs, docs.repartition(7).orderBy(F.desc("text"))) for r in T.training_rows(d, labels).where(F.col("doc_id") == hot).collect()}
    assert len(again) == 1
    seen = []
    monkeypatch.setattr(QR, "learn", lambda x, y: seen.append((len(x), int(y.sum()))) or [])
    assert QR.fit_rules(docs, labels) == [] and seen == [(6, 2)]


def test_toxicity_edges(spark):
    docs = spark.createDataFrame([(1, None, 1), (2, "", 1), (3, "some words", 1), (None, "no id", 1)], "doc_id long, text string, score int")
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert [r.score for r in T.toxicity(docs, none).collect()] == [0.0] * 4
    assert T.toxicity(docs.where("false"), none).count() == 0
    assert T.keep_clean(docs, T.fit(docs, none)).columns == docs.columns
