"""Odd inputs: nulls anywhere, empty and very long texts, ties, repeated rows, empty tables, clashing columns."""

import math
import random
from zlib import crc32

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from aggnear.llm import capfilters, chaining, idstore, langid, mixing, packing, quality, simhash, topk, urls
from aggnear.llm.common import new_folder

rnd = random.Random(4)
WORDS = ["".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(2, 7))) for _ in range(400)]


def prose(n):
    return " ".join(rnd.choice(WORDS) for _ in range(n))


LONG = prose(60_000)
SAME = prose(90)
ROWS = [
    (1, prose(120), "en", "a", 5), (2, None, "en", "a", None), (3, "", None, "b", 0), (4, " \n\t ", "en", None, 1), (None, prose(30), "en", "b", 2),
    (None, None, None, None, None), (5, SAME, "en", "a", 3), (5, SAME, "en", "a", 3), (6, SAME, "fr", "c", 3), (7, prose(40), "fr", "c", 4), (7, prose(50), "fr", "c", 4),
    (8, LONG, "en", "a", 9), (9, "12 34 !!", "en", "a", 9), (10, "é", "fr", None, 1), (11, prose(70) + " " + SAME, "en", "b", 7), (12, "<|endoftext|> x", "en", "b", 7),
]
KINDS = "doc_id long, text string, lang string, source string, n_chars long"
CLASH = ["id", "fp0", "size", "component_id", "mix_size", "mix_copies", "chain_spans", "simhash_id", "key", "n", "start", "part", "c1", "m0"]


@pytest.fixture(scope="module")
def docs(spark):
    d = spark.createDataFrame(ROWS, KINDS)
    for c in CLASH:
        d = d.withColumn(c, F.lit(f"own {c}"))
    return d.repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], KINDS)


def test_idstore(spark, docs, empty):
    folder = new_folder(spark, "t")
    idstore.write(docs, folder)
    got = idstore.read(spark, folder).collect()
    assert len(got) == len(ROWS) and idstore.verify(spark, folder)
    by_id = {}
    for r in got:
        by_id.setdefault(r.doc_id, []).append(r)
    end = crc32(np.array([1], "<u4").tobytes())
    assert all(r.n_tokens == 1 and r.ids_crc32 == end for r in by_id[2] + by_id[3] + by_id[4])
    assert by_id[8][0].n_tokens > 60_000
    last = 0
    for r in sorted(got, key=lambda r: r.start):
        assert r.start == last
        last += r.n_tokens
    folder = new_folder(spark, "t")
    idstore.write(empty, folder)
    assert idstore.read(spark, folder).count() == 0


def test_packing(docs, empty):
    got = packing.pack(docs).collect()
    assert sum(r.doc_id == 8 for r in got) == math.ceil(sum(r.length for r in got if r.doc_id == 8) / 4096)
    fill = {}
    for r in sorted(got, key=lambda r: (r.sequence_id, r.offset)):
        assert fill.get(r.sequence_id, 0) == r.offset
        fill[r.sequence_id] = r.offset + r.length
    assert max(fill.values()) <= 4096
    assert packing.pack(empty).count() == 0


def test_simhash(docs, empty):
    got = simhash.near_texts(docs).collect()
    assert len(got) == len(ROWS)
    comp = {r.doc_id: r.component_id for r in got if r.doc_id is not None}
    assert comp[5] == comp[6] == 5 and comp[2] == comp[3] == comp[4] == 2
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    rows = kept.collect()
    ids = [r.doc_id for r in rows]
    assert ids.count(5) == 1 and 6 not in ids and ids.count(None) == 2 and ids.count(7) == 1
    assert all(r["component_id"] == "own component_id" for r in rows)
    assert simhash.keep_one(empty).count() == 0 and simhash.near_texts(empty).count() == 0


def test_chaining(docs, empty):
    found = {(r.doc_id, r.ref_doc_id) for r in chaining.passages(docs).collect()}
    assert (6, 5) in found and (11, 5) in found and not any(a in (1, 2, 3, 4, 7, 8, 9, 10) for a, _ in found)
    cut = chaining.cut_passages(docs)
    assert cut.columns == docs.columns
    rows = cut.collect()
    ids = [r.doc_id for r in rows]
    assert 6 not in ids and ids.count(5) == 2 and ids.count(7) == 2 and ids.count(None) == 2
    eleven = next(r for r in rows if r.doc_id == 11)
    assert len(eleven.text.split()) == 70 and eleven.n_chars == len(eleven.text) and eleven.chain_spans == "own chain_spans"
    assert chaining.cut_passages(empty).count() == 0


def test_mixing(docs, empty):
    got = mixing.mix(docs.select("doc_id", "source", "text")).collect()
    assert len(got) == len(ROWS) and all(0 <= r.mix_copies <= 2 for r in got)
    same = [r.mix_copies for r in got if r.doc_id == 5]
    assert len(same) == 2 and same[0] == same[1]
    assert all(r.mix_size == 0 for r in got if not (r.text or "").strip())
    out = mixing.repeated(docs)
    assert out.columns == docs.columns
    assert out.count() == sum(r.mix_copies for r in got) and all(r.mix_size == "own mix_size" for r in out.collect())
    assert mixing.mix(empty).count() == 0


def test_langid(docs, empty):
    model = langid.train(docs.select("doc_id", "text", "lang"))
    got = langid.identify(docs, model).collect()
    assert len(got) == len(ROWS)
    by_text = {r.doc_id: r for r in got if r.doc_id is not None}
    assert all(by_text[i].lang_pred == "und" and by_text[i].score == 0 and by_text[i].rejected for i in (2, 3, 4, 9))
    assert by_text[10].lang_pred in ("en", "fr")
    kept = langid.keep_identified(docs, model)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} >= {1, 5, 6, 8, 11}
    none = langid.train(empty)
    assert none is None and langid.identify(docs, None).filter("lang_pred <> 'und'").count() == 0
    assert langid.identify(empty, model).count() == 0


def test_quality(spark, docs, empty):
    labels = spark.createDataFrame([(1, 1), (2, 0), (5, 1), (5, 0), (8, None), (None, 1), (11, 1), (7, 0), (12, 7)], "doc_id long, quality int")
    model = quality.train(docs, labels)
    got = quality.score(docs, model).collect()
    assert len(got) == len(ROWS) and all(0 <= r.score <= 1 for r in got)
    blank = {r.score for r in got if r.doc_id in (2, 3)}
    assert len(blank) == 1
    base = quality.train(docs, labels.filter("quality = 1"))
    assert {r.score for r in quality.score(docs, base).collect()} == {1.0}
    assert {r.score for r in quality.score(docs, quality.train(empty, labels)).collect()} == {0.5}
    assert quality.score(empty, model).count() == 0


def test_vectors(spark):
    nan, inf = float("nan"), float("inf")
    rows = [
        (100, [1.0, 0.0], 1), (101, [1.0, 0.1], 1), (102, [1.0, 0.0], 1), (103, [0.0, 0.0], 1), (104, None, 1), (105, [1.0, None], 1), (106, [nan, 1.0], 1), (107, [inf, 1.0], 1),
        (108, [1.0, 0.0], None), (109, [1.0, 0.0], 2), (110, [1.0, 0.0, 0.0], 1), (111, [], 1), (200, [0.5, 0.05], 1), (200, [0.5, 0.05], 1), (None, [1.0, 0.0], 1),
    ]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").withColumn("rep", F.lit("own"))
    got = {r.vec_id: r for r in capfilters.near_vectors(v).collect()}
    assert len(got) == 14
    assert got[100].n_links == 3 and got[200].component_id == 100 and not got[200].kept
    for i in (103, 104, 105, 106, 107, 108, 109, 110, 111):
        assert got[i].n_links == 0 and got[i].component_id == i and got[i].kept
    assert capfilters.near_vectors(v.filter("false")).count() == 0
    best = topk.top_k(v, v.filter("vec_id % 100 = 0"), 3).collect()
    first = [(r.vec_id, r.score) for r in sorted(best, key=lambda r: r.rank) if r.query_id == 100]
    assert first == [(102, 1048576), (108, 1048576), (109, 1048576)] or first[0][1] == 1048576
    assert {r.query_id for r in best} == {100, 200}
    assert topk.top_k(v.filter("false"), v.filter("false")).count() == 0
    huge = spark.createDataFrame([(100, [3e38] * 3), (1, [3e38] * 3), (2, [-3e38] * 3)], "vec_id long, embedding array<float>")
    assert [(r.vec_id, r.score) for r in topk.top_k(huge, huge.filter("vec_id = 100")).orderBy("rank").collect()] == [(1, (1 << 63) - 1), (2, -(1 << 63))]


def test_urls(spark):
    pages = spark.createDataFrame(
        [(1, None), (2, ""), (3, "no scheme"), (4, "http://"), (5, "HTTP://A.EXAMPLE.com/en/7x?q#f"), (6, "http://example.com.evil.org/es/1"), (6, "http://example.com.evil.org/es/1"),
         (None, "x://com/en/"), (7, "a://b.net?de/"), (8, "a://x.example.net/de/8/" + "y" * 50_000), (9, "a://xexample.com/en/7"), (10, "a://.com/en/")],
        "page_id long, url string",
    ).withColumn("host", F.lit("own"))
    rules = spark.createDataFrame(urls.RULES, "host string, path string, verdict string")
    got = urls.filter_urls(pages, rules).collect()
    assert len(got) == 12
    by = {r.page_id: r for r in got}
    assert (by[1].host, by[1].path, by[1].rule, by[1].verdict) == ("", "", None, "allow")
    assert by[5].rule == "example.com/en/7" and by[5].verdict == "allow" and by[6].rule == "org/es/" and by[None].rule == "com/en/"
    assert by[7].path == "" and by[8].rule == "example.net/de/8" and by[9].rule == "com/en/" and by[10].rule == "com/en/"
    assert urls.filter_urls(pages.filter("false"), rules).count() == 0
    assert urls.filter_urls(pages, rules.filter("false")).filter("rule is not null").count() == 0


def test_url_rules_are_the_contracts(spark):
    wanted = {"com/en/": "block", "example.com/en/7": "allow", "net/de/": "allow", "example.net/de/8": "block", "org/es/": "block"}
    assert {h + p: v for h, p, v in urls.RULES} == wanted
    pages = spark.createDataFrame([(1, "a://b.net/de/5"), (2, "a://example.net/de/7"), (3, "a://example.net/de/8"), (4, "a://b.net/en/")], "page_id long, url string")
    rules = spark.createDataFrame(urls.RULES, "host string, path string, verdict string")
    got = {r.page_id: (r.rule, r.verdict) for r in urls.filter_urls(pages, rules).collect()}
    assert got == {1: ("net/de/", "allow"), 2: ("net/de/", "allow"), 3: ("example.net/de/8", "block"), 4: (None, "allow")}


def test_pipeline_on_odd_and_empty_tables(spark, docs, empty):
    for table in (docs, empty):
        x = table
        for name, step in corpus_pipeline.STAGES:
            out = step(spark, x, "")
            if name != "packing":
                assert out.columns == table.columns
            path = new_folder(spark, f"t-{name}")
            out.write.parquet(path)
            x = spark.read.parquet(path)
        assert (x.count() > 0) == (table is docs)
