"""Text operators against brute force, on odd rows and small tables."""

import base64
import collections
import hashlib
import io
import re

import numpy as np
import pytest

from rayfit.llm import blocks, bpe, exact, jaccard, langid, mixing, quality, slices, urls, warc
from rayfit.llm.queries import RULES

ODD = [None, "", " ", "a", "A a\tb", "x" * 9000, "the same text of more than five words", "the same text of more than five words", "Straße ñandú 語言 <|endoftext|> tail", "a\n\n" + "b" * 5000 + "  c", "1 2 3", "tie tie tie tie tie tie"]


def table(spark, texts):
    """Texts as documents, with columns whose names could clash."""
    return spark.createDataFrame([(i, t, "en" if i % 2 else None, i, "k") for i, t in enumerate(texts)], "doc_id long, text string, lang string, id long, key string")


@pytest.fixture(scope="module")
def path():
    return pytest.importorskip("public_tokenizers").path("byte_bpe_50k.json")


def test_bpe_is_the_library(spark, path):
    tool = bpe._library(path)
    got = {r.doc_id: r for r in bpe.encode(table(spark, ODD), path).collect()}
    for i, t in enumerate(ODD):
        ids = tool.encode(t or "", add_special_tokens=False).ids
        assert np.frombuffer(got[i].ids, "<u4").tolist() == ids
        assert got[i].decoded == tool.decode(ids, skip_special_tokens=False)
    assert bpe.encode(table(spark, []), path).count() == 0


def test_tree_joins_are_exact(path):
    g = np.random.default_rng(0)
    for letters in ("ab", "aaab", "thing", "é!?"):
        data = "".join(g.choice(list(letters), 3000)).encode()
        whole = bpe.encode_piece(path, data)
        for size in (50, 700):
            assert bpe.tree(path, [bpe.encode_piece(path, data[i : i + size]) for i in range(0, len(data), size)]) == whole


def test_common_characters_agree(path):
    quick, slow = bpe._quick(path), bpe._library(path)
    for c in map(chr, range(0x250)):
        for t in ("a%sb", "1%s2", " %s ", "!%s!", " %s\n\n%s"):
            s = t.replace("%s", c)
            assert quick.encode(s, allowed_special="all") == slow.encode(s, add_special_tokens=False).ids


def test_exact_groups(spark):
    got = {r.doc_id: r for r in exact.groups(table(spark, ODD), capacity=2).collect()}
    by = collections.defaultdict(list)
    for i, t in enumerate(ODD):
        by[t or ""].append(i)
    for t, ids in by.items():
        for i in ids:
            assert (got[i].keep_id, got[i].group_size, got[i].kept, got[i].text_sha256) == (max(ids), len(ids), i == max(ids), hashlib.sha256(t.encode()).hexdigest())
    assert exact.groups(table(spark, [])).count() == 0


def shingles(t):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def test_jaccard_by_brute_force(spark):
    g = np.random.default_rng(5)
    words = [f"w{i}" for i in range(400)]
    texts = list(ODD)
    for _ in range(12):  # groups of altered copies, the original in the middle of the ids
        base = list(g.choice(words, int(g.integers(8, 260))))
        for k in range(9):
            own = list(base)
            for _ in range(0 if k == 4 else int(g.integers(1, 1 + len(base) // 25 + 1))):
                own[int(g.integers(len(own)))] = str(g.choice(words))
            texts.append(" ".join(own))
    sets = [shingles(t) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]) and sets[j]:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    got = {r.doc_id: r for r in jaccard.classes(table(spark, texts)).collect()}
    assert {i: (len(sets[i]), find(i)) for i in range(len(texts))} == {i: (r.n_shingles, r.component_id) for i, r in got.items()}
    assert jaccard.classes(table(spark, [])).count() == 0


def test_components_of_any_order(spark):
    """A chain whose ids rise, one in random order, a star around its largest id, and a random graph."""
    from rayfit.llm.components import connected

    g = np.random.default_rng(2)
    order = 1000 + g.permutation(300)
    links = [(i, i + 1) for i in range(299)] + list(zip(order.tolist(), order[1:].tolist())) + [(2000 + i, 2100) for i in range(100)] + (3000 + g.integers(0, 200, (150, 2))).tolist()
    root = {x: x for pair in links for x in pair}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    linked = {x for a, b in links if a != b for x in (a, b)}
    got = connected(spark.createDataFrame([tuple(p) for p in links] + [(None, 5), (7, 7)], "a long, b long")).collect()
    assert {r.id: r.component for r in got} == {x: find(x) for x in linked} and len(got) == len(linked)
    assert connected(spark.createDataFrame([], "a long, b long")).count() == 0


def steps(n):
    """Versions of one text, each linked to the next one only."""
    return [" ".join(f"w{10 * i + k}" for k in range(100)) for i in range(n)]


def test_jaccard_of_a_text_edited_step_by_step(spark):
    got = jaccard.classes(table(spark, steps(300))).collect()
    assert len(got) == 300 and {r.component_id for r in got} == {0}


def test_join_has_every_link(spark, monkeypatch):
    """Links within a component count too, over several blocks of it and several products."""
    monkeypatch.setattr(jaccard, "LINKED", 4)
    monkeypatch.setattr(jaccard, "TAKEN", 64)
    g = np.random.default_rng(6)
    texts = list(ODD) + steps(12) + steps(2)
    for size in (3, 25):
        base = [f"v{i}" for i in g.integers(0, 4000, 120)]
        for _ in range(size):
            own = list(base)
            for at in g.integers(0, 120, int(g.integers(0, 4))):
                own[at] = "new"
            texts.append(" ".join(own))
    sets = [shingles(t) for t in texts]
    links = {(i, j) for j in range(len(texts)) for i in range(j) if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j])}
    got = {r.doc_id: r for r in jaccard.join(table(spark, texts)).collect()}
    assert {i: r.n_links for i, r in got.items()} == {i: sum(i in p for p in links) for i in range(len(texts))}
    first = {i: min(j for j in range(len(texts)) if sets[j] == sets[i] and (sets[i] or j == i)) for i in range(len(texts))}
    assert {i: r.class_id for i, r in got.items()} == first
    rows = jaccard.pairs(table(spark, texts)).collect()
    assert {(r.a, r.b) for r in rows} == {p for p in links if first[p[0]] == p[0] and first[p[1]] == p[1] and sets[p[0]] != sets[p[1]]} and len(rows) == len(set(rows))
    assert all((r.inter, r.na, r.nb) == (len(sets[r.a] & sets[r.b]), len(sets[r.a]), len(sets[r.b])) for r in rows)
    assert jaccard.join(table(spark, [])).count() == 0


def test_histograms_bound_differences():
    g = np.random.default_rng(7)
    for n, m in ((40, 50), (300, 380), (1000, 60)):
        pool = g.integers(0, 2**63, 2000, dtype=np.uint64)
        a, b = np.unique(g.choice(pool, n)), np.unique(g.choice(pool, m))
        assert jaccard.differ([jaccard.packed(a)], [jaccard.packed(b)])[0] <= len(np.setxor1d(a, b))


def test_language_spans(spark):
    en, de = "the quick brown fox jumps over the lazy dog and runs away ", "der schnelle braune fuchs springt über den faulen hund und läuft "
    docs = spark.createDataFrame([(i, (en, de)[i % 2] * 3, ("en", "de")[i % 2]) for i in range(20)], "doc_id long, text string, lang string")
    model = langid.fit(docs)
    got = {r.doc_id: r for r in langid.label(table(spark, [None, "", "12 !", en, de, en * 3 + de * 2]), model, spans=True).collect()}
    assert [got[i].lang_pred for i in range(6)] == ["und", "und", "und", "en", "de", "en"]
    assert [s.lang for s in got[5].spans] == ["en", "de"] and 0.5 < got[5].score < 1
    assert langid.label(table(spark, ["a"]), langid.fit(docs.limit(0))).first().lang_pred == "und"


def test_viterbi_by_enumeration():
    import itertools

    g = np.random.default_rng(3)
    for _ in range(40):
        e = g.normal(0, 3, (6, 3))
        score = lambda p, e=e: sum(e[t, p[t]] for t in range(6)) - 2.0 * sum(p[t] != p[t - 1] for t in range(1, 6))
        assert score(langid.viterbi(e, 2.0)) == pytest.approx(max(map(score, itertools.product(range(3), repeat=6))))


def test_isotonic_and_quality(spark):
    assert quality.pool(np.array([1.0, 3.0, 2.0, 4.0]), np.ones(4)).tolist() == [1.0, 2.5, 2.5, 4.0]
    texts = ["Good plain words in a row. " * (1 + i % 4) if i % 2 else "BUY!! NOW!! $$$ ### " * (1 + i % 4) for i in range(60)] + [None, ""]
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, quality int")
    out = {r.doc_id: r for r in quality.classify(table(spark, texts), labels, labels.doc_id < 40).collect()}
    assert len(out) == 62 and all(0 <= r.score <= 1 for r in out.values())
    assert all(out[i].predicted == i % 2 for i in range(40, 60))
    assert {r.score for r in quality.classify(table(spark, texts), labels, labels.doc_id < 0).collect()} == {0.5}


def test_url_rules_and_list(spark):
    rows = [None, "", "no scheme", "HTTP://WWW.Example.COM/en/x?q", "http://a.example.com/en/1", "https://x.net/fr/2#t", "http://x.org", "http://bad.example.org/a.html", "https://www.bad.example.org/a/?x=1"]
    pages = spark.createDataFrame(list(enumerate(rows)), "page_id long, url string")
    got = {r.page_id: r for r in urls.judge(pages, RULES, spark.createDataFrame([("bad.example.org/a",)], "canon string")).collect()}
    assert [got[i].verdict for i in range(9)] == ["allow", "allow", "allow", "allow", "block", "block", "allow", "block", "block"]
    assert [got[i].rule for i in (3, 4, 5, 6)] == ["www.example.com/en/", "example.com/en/", "net/fr/", None]
    assert (got[3].host, got[3].path, got[6].path, got[0].host) == ("www.example.com", "/en/x", "", "")


def test_warc_round_trip_and_damage(spark):
    rows = [(5, "http://a/", "same"), (3, None, "same"), (9, "http://b/", None), (10, "x", ""), (11, "x", "é" * 100000)] + [(20 + i, "u", f"<p>page {i} of many</p>") for i in range(40)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    made = warc.write(pages)
    got = {r.page_id: r for r in warc.read(made, payload=True).collect()}
    for page, _, html in rows:
        data = (html or "").encode()
        assert got[page].payload_digest == base64.b32encode(hashlib.sha1(data).digest()).decode() and got[page].payload_bytes == len(data)
        assert got[page].payload == (data if got[page].record_type == "response" else b"")
    assert (got[5].record_type, got[5].refers_to, got[3].record_type, got[10].refers_to) == ("revisit", 3, "response", 9)
    file = made.first().file
    data = open(file, "rb").read()
    for bad in (data[:-3], b"\x00" + data[1:], data[:20]):
        with pytest.raises(warc.Damaged):
            list(warc.frames(io.BytesIO(bad)))
    with pytest.raises(warc.Damaged):
        warc.parse(warc.record(1, "u", b"abc").replace(b"abc", b"abd"))


def test_blocks(spark):
    html = '<html><head><title>T</title><script>var a="</p>";</script></head><body><nav><ul><li><a href="/">Home</a></li></ul></nav><div class="ad">Buy</div><article><h1>A &amp; B</h1><p>First  of\ntwo.<p>Second &lt;one&gt;.</article><footer>&copy; x</footer>'
    pages = spark.createDataFrame([(0, "u", html), (1, "u", None), (2, None, ""), (3, "u", "plain < text")], "page_id long, url string, html string")
    got = {r.page_id: r for r in blocks.extract(pages).collect()}
    assert got[0].text == "A & B\nFirst of two.\nSecond <one>." and got[0].n_chars == len(got[0].text)
    assert got[1].text == got[2].text == ""
    net, test = blocks.fitted(), blocks.generated(77, 60)
    right = [((net.scores(*blocks._pad([blocks.vectors(seq)]))[0] > 0) == (y > 0)).mean() for seq, y in test]
    assert np.mean(right) > 0.95


def test_dropped_elements_end_with_themselves_or_their_parent():
    texts = lambda page: [t for _, t, _ in blocks.leaves(page)]
    assert texts('<article><p>One <svg class="i"/> two.</p><p>Three.</p></article>') == ["One two.", "Three."]
    assert texts('<p>One <svg class="i"> x</p><p>Three.</p>') == ["One", "Three."]
    assert texts("<p><a>One <svg><path></a> two.</p>") == ["One two."]
    assert texts("<p>One <svg><title>t</title><path d='M0'/><g>x</g></svg> two.</p>") == ["One two."]
    assert texts("<p>One <object>x<object>y</object>z</object> two.</p>") == ["One two."]
    assert texts("<div><select><option>x<option>y</select>One<template><p>x</p></div><div>Two</div>") == ["One", "Two"]
    assert texts("<p>One<script>'</p><svg>'</script><noscript><p>x</p></noscript>two<select-all>three</select-all></p>") == ["One two", "three"]
    assert texts("One <svg><!-- </svg> --><style>a</style>x</p>y</svg> two") == ["One two"]


def test_block_vectors_read_whole_leaves():
    """Leaves that differ after word 40 only, in nothing that the counts tell, differ to the labeller."""
    head = "word " * 60
    a, b = (blocks.vectors([(("p",), head + tail, 0)])[0] for tail in ("reply comment", "total comment"))
    words = slice(blocks.PATH + blocks.LAST, blocks.PATH + blocks.LAST + blocks.WORD)
    assert (a[words] != b[words]).any() and a[words].sum() == pytest.approx(1) and np.delete(a, range(*words.indices(len(a)))).tolist() == np.delete(b, range(*words.indices(len(b)))).tolist()


def test_topk_by_brute_force(spark):
    g = np.random.default_rng(9)
    x = g.normal(0, 0.3, (400, 12))
    x[7] = x[8] = x[9]
    rows = [(i, [float(v) for v in x[i]]) for i in range(400)] + [(400, None), (401, [1.0] * 11 + [float("nan")]), (402, [None] * 12), (403, [0.0] * 12)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    from pyspark.sql import functions as F

    got = collections.defaultdict(list)
    for r in slices.search(df, F.col("vec_id") % 50 == 0, 5).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    v = np.floor(256 * np.vstack([x, np.zeros((4, 12))])).astype(int)
    ids = [*range(400), 403]
    for q in range(0, 400, 50):
        best = sorted(((i, int(v[i] @ v[q])) for i in ids if i != q), key=lambda p: (-p[1], p[0]))[:5]
        assert got[q] == best
    assert set(got) == set(range(0, 400, 50))


def test_mixing_meets_targets(spark):
    texts = ["good plain words here. " * 5 if i % 3 else "vile nasty slur words. " * 5 for i in range(90)] + [None]
    labels = spark.createDataFrame([(i, "good" if i % 3 else "bad") for i in range(60)], "doc_id long, domain string")
    rows = mixing.mix(table(spark, texts), labels, {"good": 0.8, "bad": 0.2}, "good").collect()
    good, bad = (sum(r.tokens * r.rate * r[f"p_{d}"] for r in rows) for d in ("good", "bad"))
    assert good / (good + bad) == pytest.approx(0.8, abs=0.01) and all(r.rate >= 0 for r in rows) and len(rows) == 91


def test_mixture_stage_meets_shares(spark, tmp_path):
    """Token shares of what the stage writes, with one domain below its target and one that is not wanted."""
    import corpus_pipeline
    from rayfit.llm.queries import SHARES

    g = np.random.default_rng(4)
    words = {"good": "plain calm words about rivers towns bread music".split(), "low": "buy cheap pills win prize click offer cash".split(), "toxic": "vile nasty slur filth hate scum rot curse".split()}
    kinds = ["low" if i % 50 == 1 else "toxic" if i % 100 == 2 else "good" for i in range(3000)]
    docs = table(spark, [" ".join(g.choice(words[k], 20)) for k in kinds]).withColumnsRenamed({"id": "n_chars", "key": "source"})
    rows = [(i, int(k == "good"), int(k == "toxic")) for i, k in enumerate(kinds)]
    spark.createDataFrame(rows, "doc_id long, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    out = corpus_pipeline._mixture(spark, docs, str(tmp_path)).select("doc_id", "text").collect()
    tokens = collections.Counter()
    for r in out:
        tokens[kinds[r.doc_id]] += len(r.text.split())
    assert kinds.count("low") / len(kinds) == 0.02
    for k, share in SHARES.items():
        assert tokens[k] / sum(tokens.values()) == pytest.approx(share, abs=0.006), tokens


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    n = docs.count()
    for name, stage in corpus_pipeline.STAGES[:3]:
        out = stage(spark, docs, "/root/testdata/sf0.001")
        assert tuple(out.columns) == corpus_pipeline.COLUMNS and 0 < out.count() <= n, name
        docs = out


def test_staged_tables_pass_small_batches(spark):
    """Wide rows come in batches of about BATCH_BYTES, and the session's own setting is back afterwards."""
    import pyarrow as pa
    from pyspark.sql import functions as F

    from rayfit.llm import common

    def sizes(batches):
        for b in batches:
            yield pa.record_batch([pa.array([b.nbytes]), pa.array([b.num_rows])], ["size", "n"])

    wide = spark.range(0, 3000, 1, 1).select("id", F.repeat(F.lit("x"), 8000).cast("binary").alias("held"))
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    got = common.staged(wide.mapInArrow(sizes, "size long, n long"), "sizes").agg(F.max("size"), F.sum("n")).first()
    assert got[0] <= common.BATCH_BYTES + 10_000 and got[1] == 3000
    assert spark.conf.get(key) == before
