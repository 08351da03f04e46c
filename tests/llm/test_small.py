"""Hard rows: nulls, empty and long texts, repeated rows, ties, empty tables, clashing column names."""

import random

import corpus_pipeline
import numpy as np
import pytest
from pyspark.sql import functions as F

from probgraph.llm import decontamination, licenses, mixing, near_dedup, quality_classifier, quality_rules, substring_dedup, suffix_dedup, token_counts, url_filter

R = random.Random(3)
VOCAB = ["".join(R.choices("aeioulnrst", k=R.randint(2, 8))) for _ in range(3000)]
prose = lambda n: " ".join(R.choices(VOCAB, k=n))
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = ["score", "keep", "n_words", "n_tokens", "distance2", "rejected", "repetition", "dup_keys", "node", "n", "h", "size", "weight", "label", "line", "key", "mix_key", "stat_group", "dup_doc", "dup_spans", "doc", "text_key"]


def hard_rows():
    base = prose(120)
    out = [(i, prose(R.randint(60, 140)), R.choice(["en", "de"]), f"s{i % 3}", 1) for i in range(40)]
    out += [(100, base, "en", "s0", 1), (101, base, "en", "s1", 1), (101, base, "en", "s1", 1), (102, base + " " + prose(2), None, None, None)]
    out += [(110, None, "en", "s0", 0), (110, None, "en", "s0", 0), (111, "", "en", "s0", 0), (112, "  \n ", None, "s1", 3), (113, "!!! ???", "en", "s1", 7), (114, "word", "en", "s2", 4)]
    out += [(None, prose(80), "en", "s0", 1), (None, "x y", None, None, None), (120, prose(30000), "en", "s0", 1)]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    df = spark.createDataFrame(hard_rows(), SCHEMA)
    for c in CLASH:
        df = df.withColumn(c, F.lit("clash"))
    return df.cache()


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def test_token_counts(docs, none):
    got = token_counts.token_counts(docs)
    assert got.count() == docs.count() and got.columns.count("n_tokens") == 1
    assert {(r.doc_id, r.n_words, r.n_tokens) for r in got.filter("doc_id in (110, 111, 112)").collect()} == {(110, 0, 0), (111, 0, 0), (112, 0, 0)}
    assert token_counts.token_counts(none).count() == 0


def test_mixing(docs, none):
    got = mixing.mix_sources(docs)
    assert got.columns == [c for c in docs.columns if c != "repetition"] + ["repetition"]
    assert got.filter("source is null").count() > 0
    assert mixing.mix_sources(none).count() == 0
    assert mixing.mix_sources(docs, {"s0": 1.0}).filter("source is null or source <> 's0'").count() == 0


def test_quality_rules(docs, none):
    got = quality_rules.judged(docs)
    assert got.count() == docs.count()
    assert all(r.rejected for r in got.filter("doc_id in (110, 111, 112)").collect())
    kept = quality_rules.kept(docs)
    assert kept.columns == docs.columns and kept.filter("doc_id < 40").count() == 40
    assert quality_rules.judged(none).count() == 0 and quality_rules.kept(none).count() == 0


def test_classifier(spark, docs, none):
    labels = spark.createDataFrame([(i, int(i % 3 > 0)) for i in range(40)] + [(1, 0), (None, 1), (5, None)], "doc_id long, quality int")
    model = quality_classifier.fit(docs, labels)
    got = quality_classifier.score(docs, model)
    assert got.count() == docs.count() and got.filter("score is null").isEmpty()
    empty = quality_classifier.fit(none, labels)
    assert not empty[0].any() and quality_classifier.score(none, empty).count() == 0


def test_licenses(spark, docs, none):
    assert licenses.license_scan(docs).isEmpty() and licenses.license_scan(none).isEmpty()
    d = spark.createDataFrame([(1, "a\nReleased under the MIT license\nb"), (2, "Licensed under the Apache\nLicense, Version 2.0"), (3, "my license to drive"), (4, "This work is licensed under the GNU General Public License, version 2."), (5, None), (6, "Permission is hereby granted to all of you")], "doc_id long, text string")
    assert {(r.doc_id, r.line, r.license) for r in licenses.license_scan(d).collect()} == {(1, 1, "mit-notice"), (2, 0, "apache-2.0-notice"), (4, 0, "gpl-2.0-notice")}


def test_wrapped_licenses():
    """Every template is found once, at its first line, at each width; words before and after it don't matter."""
    import textwrap

    scanner = licenses.Scanner()
    for name, (wording, _) in licenses.TEMPLATES.items():
        for width in (1, 12, 20, 30, 40, 50, 60, 72, 400):
            lines = textwrap.wrap(wording, width, break_long_words=False)
            got = scanner.lines("\n".join(["my license to drive", "", prose(9), *["# " + x for x in lines], prose(9)]))
            assert [(g[0], g[1], g[3]) for g in got] == [(3, name, 0)], (name, width)
    assert [g[:2] for g in scanner.lines("Licensed under CC BY 4.0. Released under the\n\nMIT License.")] == [(0, "cc-by-4.0-notice")]
    assert [g[:2] for g in scanner.lines("Released under the\nMIT License. Licensed under\nCC BY 4.0.")] == [(0, "mit-notice"), (1, "cc-by-4.0-notice")]


def test_decontamination(spark, docs, none):
    item = prose(40).split()
    edited = item[:10] + ["zzz"] + item[11:20] + item[21:]
    bench = spark.createDataFrame([(1, " ".join(item)), (2, None), (3, ""), (4, "word"), (5, " ".join(item))], "item_id long, text string")
    more = spark.createDataFrame([(500, prose(50) + " " + " ".join(item) + " " + prose(9)), (501, prose(5) + " " + " ".join(edited)), (502, " ".join(item[:25]))], "doc_id long, text string")
    got = decontamination.contamination(docs.select("doc_id", "text").unionByName(more), bench)
    assert {(r.doc_id, r.item_id, r.start_word, r.end_word, r.edits) for r in got.collect()} == {(500, 1, 50, 90, 0), (500, 5, 50, 90, 0), (501, 1, 5, 44, 2), (501, 5, 5, 44, 2), (114, 4, 0, 1, 0)}
    assert {r.doc_id for r in decontamination.clean(more, bench).collect()} == {502}
    assert decontamination.clean(docs, bench).columns == docs.columns
    assert decontamination.contamination(none, bench).isEmpty() and decontamination.contamination(docs, bench.limit(0)).isEmpty()
    assert decontamination.contamination(more, bench, slice_items=1).count() == got.filter("doc_id >= 500").count()


def test_passages(docs, none):
    for f in (suffix_dedup.suffix_dedup, substring_dedup.substring_dedup):
        got = {(r.doc_id, r.start_word, r.end_word, r.first_doc_id) for r in f(docs).collect()}
        assert {g for g in got if g[0] in (100, 101, 102)} == {(101, 0, 120, 100), (102, 0, 120, 100)}
        assert f(none).isEmpty()
    left = suffix_dedup.without(docs)
    assert left.columns == docs.columns
    assert left.filter("doc_id = 101").isEmpty() and len(left.filter("doc_id = 102").first().text.split()) == 2
    assert left.filter("doc_id = 110").count() == 2 and left.filter("doc_id < 40").exceptAll(docs.filter("doc_id < 40")).isEmpty()


def test_near(docs, none):
    assert {tuple(r) for r in near_dedup.near_dedup(docs).filter("doc_id >= 100").collect()} == {(100, 102), (101, 102)}
    left = near_dedup.deduplicated(docs)
    assert left.columns == docs.columns and left.filter("doc_id in (100, 101)").isEmpty()
    assert left.filter("doc_id = 110").count() == 1 and left.filter("doc_id < 40").count() == 40 and left.filter("doc_id is null").count() == 2
    assert near_dedup.near_dedup(none).isEmpty() and near_dedup.deduplicated(none).isEmpty()


def test_urls(spark):
    urls = [None, "", "not a url", "http://WWW.Evil.example/", "https://evil.example/a/b.html?x=1", "http://u:p@ok.example:80/bad/", "https://m.ok.example/bad#z", "http://ok.example/fine", "http://ok.example/fine"]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, key string").withColumn("hit", F.lit(1))
    listed = spark.createDataFrame([("http://evil.example",), ("ok.example/bad",), (None,), ("http://evil.example/",)], "url string")
    for most in (10, 0):
        got = url_filter.url_filter(pages, listed, most)
        assert {r.page_id for r in got.filter("listed").collect()} == {3, 4, 5, 6} and got.count() == len(urls)
    assert url_filter.url_filter(pages, listed.limit(0)).filter("listed").isEmpty()
    assert url_filter.url_filter(pages.limit(0), listed).isEmpty()


def test_pipeline(spark, docs, none, tmp_path):
    spark.createDataFrame([(1, prose(30))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    got = corpus_pipeline.run(spark, str(tmp_path))
    assert got.count() > 0 and set(got.columns) == set(docs.columns)
    for _, f in corpus_pipeline.STAGES:
        assert f(spark, none, str(tmp_path)).count() == 0
    assert np.isfinite(got.count())
