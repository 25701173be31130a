"""The corpus pipeline against brute force."""

import re
import zlib

import corpus_pipeline
from gossamer.llm import common, lang_mixture, secret_cnn

from .test_operators import ODD, SCHEMA, brute_components, check_packing, fingerprint_of, rows_of


def test_stages_take_effect(spark, medium):
    docs = common.table(spark, medium, "documents")
    texts = {d.doc_id: d.text for d in docs.collect()}
    lettered = {i: t for i, t in texts.items() if t and any(c.isalpha() for c in t)}
    kept = corpus_pipeline.language_id(spark, docs, medium)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == set(lettered)
    one = corpus_pipeline.near_dedup(spark, kept, medium)
    groups = brute_components(sorted((i, fingerprint_of(t)) for i, t in lettered.items()))
    assert one.columns == docs.columns and sorted(r.doc_id for r in one.collect()) == sorted({*groups.values()})
    clean = corpus_pipeline.secret_scan(spark, one, medium)
    rows = {r.doc_id: r for r in clean.collect()}
    for i, r in rows.items():
        base = secret_cnn.base_findings(lettered[i])
        assert r.n_chars == len(r.text) and not secret_cnn.base_findings(r.text)
        if not base and not re.search(r"<learnt>", r.text):
            assert r.text == lettered[i]
    packed = corpus_pipeline.packing(spark, clean, medium).collect()
    n, least = check_packing(packed, {i: r.text for i, r in rows.items()})
    assert n <= 1.02 * least + 1
    assert sorted(map(tuple, ((r.doc_id, r.piece, r.ids_crc32) for r in corpus_pipeline.run(spark, medium).collect()))) == sorted((r.doc_id, r.piece, r.ids_crc32) for r in packed)


def test_odd_rows_pass_every_stage(spark):
    rows = rows_of(ODD)
    docs = spark.createDataFrame([*rows, rows[3], (None, "null id here", "en", None, None, None, None, None, None), (None, "null id here", "en", None, None, None, None, None, None)], SCHEMA)
    for start in (docs, docs.limit(0)):
        now = start
        for name, stage in corpus_pipeline.STAGES[:-1]:
            now = stage(spark, now, "")
            assert now.columns == docs.columns, name
        last = corpus_pipeline.packing(spark, now, "")
        assert last.count() >= now.count() and now.where("doc_id is null").count() == (start.count() > 0)


def test_each_group_keeps_one_row_whatever_its_ids(spark):
    a, b, c = (" ".join(f"{w}{k} is here" for k in range(40)) for w in "abc")
    rows = [(7, a), (7, b), (8, b), (2, c), (5, c), (5, a.upper() + " x y z"), (5, "alone with its own words"), (5, "alone with its own words")]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t), None, None, None, None) for i, t in rows], SCHEMA)
    groups = brute_components([(k, fingerprint_of(t)) for k, (_, t) in enumerate(rows)])
    want = sorted(min(rows[k] for k in groups if groups[k] == g) for g in {*groups.values()})
    got = corpus_pipeline.near_dedup(spark, docs, "")
    assert got.columns == docs.columns and sorted((r.doc_id, r.text) for r in got.collect()) == want
    assert {(7, a), (7, b), (2, c), (5, "alone with its own words")} <= {*want}


def test_no_learnt_language_rejects_no_lettered_text(spark):
    texts = ["some words", None, "12 34", "", "日本語", "more words"]
    docs = spark.createDataFrame([(i, t, None, "s", 1, None, None, None, None) for i, t in enumerate(texts)], SCHEMA)
    held = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 5 == 0)  # the only label, in the held-out fifth
    for start in (docs, docs.unionByName(docs.where("doc_id = 0").selectExpr(f"{held}L AS doc_id", "'held out' AS text", "'en' AS lang", *docs.columns[3:]))):
        got = corpus_pipeline.language_id(spark, start, "")
        assert got.columns == docs.columns and sorted(r.text for r in got.collect()) == sorted(r.text for r in start.collect() if r.text and any(c.isalpha() for c in r.text))


def test_lettered_documents_go_because_of_their_language(spark, medium):
    docs = common.table(spark, medium, "documents").select("doc_id", "text", "lang", "source", "n_chars")
    strange = ["これは日本語の文章です。" * 20, "Это русский текст о погоде и городе. " * 12, "zqxj vkwq xzzq jjqv kqzx wvvq " * 15]
    more = spark.createDataFrame([(10**9 + i, t, None, "s", len(t)) for i, t in enumerate(strange)], docs.schema)
    got = {r.doc_id for r in corpus_pipeline.language_id(spark, docs.unionByName(more), medium).collect()}
    assert not got & set(range(10**9, 10**9 + 3))
    assert got == {r.doc_id for r in docs.collect() if r.text and any(c.isalpha() for c in r.text)}
    english = lang_mixture.kept(docs, languages=frozenset({"en"})).groupBy("lang").count().collect()
    by = {r.lang: r["count"] for r in english}
    assert by["en"] > 0.95 * docs.where("lang = 'en' and text is not null").count() and sum(v for k, v in by.items() if k not in ("en", None)) < 0.02 * by["en"]
    sure = lang_mixture.kept(docs, least=0.999).count()
    assert 0 < sure <= len(got)
