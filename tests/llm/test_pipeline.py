import random

import numpy as np
import public_tokenizers as P
from test_corpus_operators import brute_components, perturbed
from test_text_operators import check_pieces

import corpus_pipeline as C
from couponspark.llm.secret_scan import candidates, placeholder
from couponspark.llm.word_bpe import word_bpe

SMALL = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    kept, last = docs, None
    for name, step in C.STAGES[:-1]:
        out = step(spark, kept, SMALL).cache()
        assert out.columns == docs.columns and out.dtypes == docs.dtypes, name
        assert 0 < out.count() <= kept.count()
        kept = out
    last = C.STAGES[-1][1](spark, kept, SMALL).collect()
    lib, texts = word_bpe(P.path("word_bpe_49k.json")).library, {r.doc_id: r.text for r in kept.collect()}
    total = {d: len(lib.encode(t, add_special_tokens=False).ids) + 1 for d, t in texts.items()}
    got = {}
    for r in last:
        got[r.doc_id] = got.get(r.doc_id, 0) + r.length
    assert got == total


def test_run_equals_stages_and_repeats(spark):
    a, b = (sorted((r.doc_id, r.start, r.length, r.doc_tokens) for r in C.run(spark, SMALL).collect()) for _ in range(2))
    tokens = lambda rows: sorted({(d, t) for d, _, _, t in rows})
    assert tokens(a) == tokens(b) and len(a) > 0
    assert np.sum([n for _, _, n, _ in a]) == np.sum([n for _, _, n, _ in b])


def test_copied_example_survives(spark, tmp_path):
    """A key that eight sources hold is an example, though earlier stages drop its copies; one source's key goes; cuts make no secret."""
    rng = np.random.default_rng(3)
    word = lambda n: " ".join("".join(rng.choice(list("abcdefghijkm"), 6)) for _ in range(n))
    tutorial = word(60) + " password = Abcdef123456 and so on " + word(60)
    lead = word(40)
    rows = [(i, tutorial if i < 4 else word(30) + " " + tutorial + " " + word(30), "en", f"s{i}", 0) for i in range(8)]
    rows += [(20, word(50) + " password = Zyxwvu987654 " + word(50), "en", "s1", 0)]
    rows += [(30, lead + " end", "en", "s2", 0), (31, word(40) + " 0123456789abcdef" + lead + "0123456789abcdef " + word(40), "en", "s3", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    kept = docs
    for name, step in C.STAGES[1:4]:
        kept = step(spark, kept, str(tmp_path))
        if name != "secret_scan":
            kept = kept.cache()
    left = {r.doc_id: r.text for r in kept.collect()}
    assert left[0] == tutorial and {1, 2, 3} & set(left) == set()
    assert "Zyxwvu987654" not in left[20] and "[removed]" in left[20]
    assert " 0123456789abcdef\n0123456789abcdef " in left[31]


def cut_texts(docs, n=50):
    """Texts without the characters that strings of ``n`` bytes cover which also start in a document with a smaller id; a line break keeps words apart."""
    first, out = {}, {}
    for d in sorted(docs):
        x = docs[d].encode()
        for j in range(len(x) - n + 1):
            first.setdefault(x[j : j + n], d)
    for d, text in docs.items():
        x = text.encode()
        gone = [False] * len(x)
        for j in range(len(x) - n + 1):
            if first[x[j : j + n]] < d:
                gone[j : j + n] = [True] * n
        at, parts = 0, []  # runs of (gone, characters)
        for c in text:
            m = len(c.encode())
            g = all(gone[at : at + m])
            at += m
            if parts and parts[-1][0] == g:
                parts[-1][1].append(c)
            else:
                parts.append((g, [c]))
        new = []
        for i, (g, cs) in enumerate(parts):
            if not g:
                new += cs
            elif 0 < i < len(parts) - 1 and not {parts[i - 1][1][-1], parts[i + 1][1][0]} & set(" \t\n\v\f\r"):
                new.append("\n")
        out[d] = "".join(new)
    return out


def hide_by_force(docs, corpus):
    """Texts with the live values of ``docs`` replaced; ``corpus``: (text, source, lang) of all documents."""
    held, out = {}, {}
    for text, source, lang in corpus:
        for _, _, _, value in candidates(text):
            held.setdefault(value, set()).add((source, f"{source}/{lang}"))
    for d, text in docs.items():
        spans = []
        for _, s, e, value in candidates(text):
            owners = {o for o, _ in held[value]} if value in held else {None}
            example = len(owners) >= 4 or len(owners) > 1 and len(held[value]) >= 8
            if not example and not placeholder(value):
                if spans and s < spans[-1][1]:
                    spans[-1][1] = max(e, spans[-1][1])
                else:
                    spans.append([s, e])
        for s, e in reversed(spans):
            text = text[:s] + "[removed]" + text[e:]
        out[d] = text
    return out


def test_run_equals_brute_force(spark, tmp_path, monkeypatch):
    """Every piece that run() packs, against near-duplicates, cuts, secrets and ids by brute force; the fitted scorer is held fixed."""
    rng = random.Random(11)
    word = lambda n: " ".join("".join(rng.choice("abcdefghijkmé") for _ in range(6)) for _ in range(n))
    base, passage = word(80).split(), word(70)
    rows = [tuple(r) for r in spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text", "lang", "source", "n_chars").collect()]
    rows += [(5000 + i, perturbed(rng, base, i), "en", f"s{i}", 0) for i in range(6)]
    rows += [(5100 + i, f"{word(30)} {passage} api_key: Qwerty99887766 {word(30)}", "en", f"o{i}", 0) for i in range(5)]
    rows += [(5200 + i, f"{word(40)}{passage[:200]}{word(40)} secret = Only{i}Owner{i}77 {word(20)}", "de", "one", 0) for i in range(3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    docs.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    labels.write.parquet(f"{tmp_path}/labels.parquet")
    net = C.fit(docs, labels)
    monkeypatch.setattr(C, "fit", lambda *_: net)
    got = C.run(spark, str(tmp_path)).collect()

    clean = {r[0]: r[1] or "" for r in rows if net.scores([(r[1] or "").encode()])[0] < 0.3}
    groups = brute_components(list(clean.items()))
    one = {d: x for d, x in clean.items() if groups[d][0] == 0 or groups[d][1] == d}
    cut = cut_texts(one)
    hidden = hide_by_force(cut, [(r[1] or "", r[3] or "", r[2]) for r in rows])
    assert 5000 in one and 5001 not in one and any(cut[d] != one[d] for d in (5101, 5102)) and any("[removed]" in x for x in hidden.values())
    assert "Qwerty99887766" in hidden[5100] and "Qwerty99887766" not in cut[5101]  # the first copy keeps an example; the others lose it with the passage
    lib = word_bpe(P.path("word_bpe_49k.json")).library
    check_pieces(got, lambda d: [*lib.encode(hidden[d], add_special_tokens=False).ids, 2], 4096)
    assert {r.doc_id for r in got} == set(hidden)


def test_stages_on_odd_tables(spark, tmp_path):
    """Nulls in any column, repeated rows, a long text, clashing column names, and a table without rows go through all stages."""
    long = " ".join(f"w{i}x{i * 7 % 1013}" for i in range(40000))
    schema = "doc_id long, text string, lang string, source string, n_chars long, __key int, __spans string, __gone int, __block int, key string, score double, row int"
    rows = [(1, long, "en", "a", len(long)), (2, None, "en", "b", None), (3, "", None, None, 0), (None, "text without an id " * 3, "en", "c", None), (4, "alone here", "en", "a", 10), (4, "alone here", "en", "a", 10), (5, "  \n ", "en", "b", 4)]
    extra = (1, "s", 2, 3, "k", 0.5, 4)
    docs = spark.createDataFrame([(*r, *extra) for r in rows], schema)
    for name, table in (("full", docs), ("none", docs.where("false"))):
        d = f"{tmp_path}/{name}"
        table.write.parquet(f"{d}/documents.parquet")
        spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
        kept = spark.read.parquet(f"{d}/documents.parquet")
        for stage, step in C.STAGES[:-1]:
            out = step(spark, kept, d).cache()
            assert out.dtypes == docs.dtypes, stage
            assert out.count() <= kept.count()
            kept = out
        rest = kept.collect()
        pieces = C.STAGES[-1][1](spark, kept, d).collect()
        if name == "none":
            assert rest == [] and pieces == []
            continue
        assert {r.doc_id for r in rest} == {1, 2, 3, 4, 5, None} and {tuple(r[5:]) for r in rest} == {extra}
        assert {r.doc_id: r.text for r in rest}[1] == long
        size = {r.doc_id: r.doc_tokens for r in pieces}
        assert sum(r.length for r in pieces) == sum(size[r.doc_id] for r in rest)
