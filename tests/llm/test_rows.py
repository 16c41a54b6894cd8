"""Empty tables, clashing columns, null and repeated keys for every operator, and the pipeline's stages against plain loops."""

import collections
import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from rayfit.llm import blocks, bpe, exact, jaccard, langid, mixing, quality, slices, urls, warc
from rayfit.llm.queries import RULES, SHARES, vocabulary

EXTRA = "key string, id long, text2 string, hash long, x double, tokens long, rate double, label int, held string, rows int"
BLANK = ("k", 1, "t", 2, 0.5, 3, 1.0, 4, "h", 5)


@pytest.fixture(scope="module")
def path():
    pytest.importorskip("public_tokenizers")
    return vocabulary()


def wide(spark, rows, kinds):
    """Rows with columns whose names the operators use inside."""
    return spark.createDataFrame([(*r, *BLANK) for r in rows], f"{kinds}, {EXTRA}")


def test_document_operators_on_odd_tables(spark, path):
    texts = ["one two three four five six", "one two three four five six", None, "", "ein haus am see mit wald und wiese", "x " * 3000, "!!! ???"]
    for rows in ([], [(i, t) for i, t in enumerate(texts)], [(None, "a b c d e f"), (7, None), (7, None), (8, "a b c d e f"), (None, None)]):
        docs = wide(spark, rows, "doc_id long, text string").withColumns({"lang": F.lit("en"), "source": F.lit("s"), "n_chars": F.lit(1)})
        labels = wide(spark, [(0, 1, 0), (1, 0, 0), (1, 1, 0), (None, 1, 1), (4, None, None), (8, 1, 0)], "doc_id long, quality int, toxic int")
        domain = labels.select("doc_id", F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "low").alias("domain"))
        n = len(rows)
        assert bpe.encode(docs, path).count() == n
        scored = quality.classify(docs, labels, labels.doc_id.isNotNull()).collect()
        assert len(scored) == n and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in scored)
        told = langid.label(docs, langid.fit(docs)).collect()
        assert len(told) == n and all(r.lang_pred in ("en", "und") for r in told)
        mixed = mixing.mix(docs, domain, {"good": 0.9, "low": 0.1}, "good").collect()
        assert len(mixed) == n and all(r.rate >= 0 for r in mixed)
        assert exact.groups(docs).count() == n and exact.keep_last(docs).columns == docs.columns
        assert jaccard.join(docs).count() == n and jaccard.keep_first(docs).columns == docs.columns


def test_page_operators_on_odd_tables(spark):
    for rows in ([], [(1, None, None), (2, "http://a.net/fr/x", "<p>x</p>"), (3, "no scheme", ""), (4, "http://a.net/fr/x", "<p>x</p>")]):
        pages = wide(spark, rows, "page_id long, url string, html string")
        assert urls.judge(pages, RULES, spark.createDataFrame([], "canon string")).count() == len(rows)
        assert warc.read(warc.write(pages)).count() == len(rows)
        assert blocks.extract(pages).count() == len(rows)


def test_vector_operator_on_odd_tables(spark):
    assert slices.search(wide(spark, [], "vec_id long, embedding array<float>"), F.col("vec_id") % 50 == 0).count() == 0
    rows = wide(spark, [(0, [1.0]), (1, []), (2, None), (3, [None]), (4, [2.0]), (None, [3.0])], "vec_id long, embedding array<float>")
    assert [(r.query_id, r.vec_id) for r in slices.search(rows.filter("vec_id is not null"), F.col("vec_id") % 50 == 0).collect()] == [(0, 4)]


def test_stages_against_loops(spark, path, tmp_path):
    """run() on a small corpus: what each stage should keep, by plain loops; the mixture's rates by the operator."""
    import corpus_pipeline

    g = np.random.default_rng(11)
    words = {"good": "plain calm words about rivers towns bread music and the sea".split(), "low": "buy cheap pills win prize click offer cash now free".split(), "toxic": "vile nasty slur filth hate scum rot curse ugly bad".split()}
    kinds = ["low" if i % 9 == 1 else "toxic" if i % 11 == 2 else "good" for i in range(150)]
    texts = [" ".join(g.choice(words[k], 40)) for k in kinds]
    texts[10] = texts[20] = texts[30]
    texts[40], texts[41], texts[42] = None, "", "12 !?"
    texts[51] = texts[50] + " end"
    texts[53] = "new " + texts[52]
    docs = [(i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(docs, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(str(tmp_path / "documents.parquet"))
    labels = spark.createDataFrame([(i, int(k == "good"), int(k == "toxic")) for i, k in enumerate(kinds)], "doc_id long, quality int, toxic int")
    labels.write.parquet(str(tmp_path / "labels.parquet"))

    kept = {i: t for i, t, *_ in docs if t and re.search(r"[^\W\d_]", t)}
    last = {t: i for i, t in sorted(kept.items())}
    kept = {i: t for i, t in kept.items() if last[t] == i}
    sets = {i: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} for i, t in kept.items() for w in [t.lower().split()]}
    root = {i: i for i in kept}

    def find(x):
        return x if root[x] == x else find(root[x])

    for a in kept:
        for b in kept:
            if a < b and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    kept = {i: t for i, t in kept.items() if find(i) == i}
    assert {51, 53, 10, 20, 40, 41, 42}.isdisjoint(kept) and {30, 50, 52} <= set(kept)

    rest = spark.createDataFrame(list(kept.items()), "doc_id long, text string")
    domain = labels.select("doc_id", F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "low").alias("domain"))
    copies = {r.doc_id: r.copies for r in mixing.mix(rest, domain, SHARES, "good").collect()}
    assert set(copies) == set(kept) and sum(copies[i] for i in kept if kinds[i] == "toxic") <= 2
    tool = bpe._library(path)
    got = collections.defaultdict(list)
    for r in corpus_pipeline.run(spark, str(tmp_path)).collect():
        got[r.doc_id].append((r.n_tokens, r.ids_sha256, r.decoded_sha256))
    want = {}
    for i, t in kept.items():
        ids = tool.encode(t, add_special_tokens=False).ids
        own = (len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(tool.decode(ids, skip_special_tokens=False).encode()).hexdigest())
        if copies[i]:
            want[i] = [own] * copies[i]
    assert dict(got) == want
