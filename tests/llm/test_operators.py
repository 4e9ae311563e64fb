"""Each operator against brute force, an exact round trip or held-out accuracy."""

import math
import random
from collections import Counter
from zlib import crc32

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from aggnear.llm import capfilters, chaining, idstore, langid, mixing, packing, quality, simhash, tokens, topk, urls
from aggnear.llm.common import new_folder
from aggnear.llm.components import components
from aggnear.llm.features import gram_counts

D = "/root/testdata/sf0.01"
PATH = tokens.default_path()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{D}/documents.parquet")


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.select("doc_id", "text").collect()}


@pytest.fixture(scope="module")
def ids(texts):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(PATH)
    return {i: np.array(t.encode(x, add_special_tokens=False).ids + [1], "<u4") for i, x in texts.items()}


def test_words_encode_like_whole_texts():
    e, rnd = tokens.Encoder(PATH), random.Random(5)
    atoms = ["it's", "IT'S", "don't.", "x,", "X.", "9,", "é,", "É.", "J̌", "ǰ", "Å", "~", "a~b", "<|endoftext|>", "<|ENDOFTEXT|>", "a<|startoftext|>b", " ", "\x1c", "\x85", "﻿", "ß", "ẞ",
             "İ", "Σ", "ΣΑΣ", "中文字", "日本,", "🙂", "...", ",.", "'", "''s", "a's,b", "́", "가", "K", "ﬁ", "\n", "\t", "\x0b", "\x00", "123", "1.5,", "a.", "A.,", "z.'s", "’s", "École", "Straße", "ǅ", "Ÿ"]
    for _ in range(1500):
        s = "".join(rnd.choice(atoms) + rnd.choice([" ", "", "  ", "\n"]) for _ in range(rnd.randint(0, 12)))
        assert e.ids([s.encode()])[0].tolist() == e.tokenizer.encode(s, add_special_tokens=False).ids + [1], repr(s)


def test_idstore_round_trip(spark, docs, ids):
    folder = new_folder(spark, "t")
    idstore.write(docs, folder)
    start = 0
    for r in sorted(idstore.read(spark, folder).collect(), key=lambda r: r.doc_id):
        own = ids[r.doc_id]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(own), crc32(own.tobytes()))
        start += len(own)
    back = idstore.documents_of(spark, folder, docs.select("doc_id")).collect()
    assert len(back) == len(ids) and all(np.array_equal(r.ids, ids[r.doc_id]) for r in back)
    chunks = spark.read.parquet(f"{folder}/chunks")
    assert chunks.count() == chunks.select("digest").distinct().count()
    assert spark.read.parquet(f"{folder}/recipes").select(F.sum(F.size("digests"))).first()[0] > chunks.count()  # copies are stored once


@pytest.mark.parametrize("what", ["chunk", "recipe", "recipe order", "recipe gone", "document id", "manifest", "store", "nothing"])
def test_idstore_finds_damage(spark, docs, what):
    folder = new_folder(spark, "t")
    idstore.write(docs.limit(60), folder)

    def put(name, change):
        x = spark.createDataFrame(change([r.asDict() for r in spark.read.parquet(f"{folder}/{name}").collect()]), spark.read.parquet(f"{folder}/{name}").schema)
        x.write.mode("overwrite").parquet(f"{folder}/{name}2")
        spark.read.parquet(f"{folder}/{name}2").write.mode("overwrite").parquet(f"{folder}/{name}")

    def first(rows, **new):
        rows[0].update(new)
        return rows

    if what == "chunk":
        put("chunks", lambda r: first(r, payload=bytes([r[0]["payload"][0] ^ 1]) + bytes(r[0]["payload"][1:])))
    elif what == "recipe":
        put("recipes", lambda r: first(r, digests=[r[1]["digests"][0], *r[0]["digests"][1:]]))
    elif what == "recipe order":
        put("recipes", lambda r: [*first(r, row=r[1]["row"] + 1)[:1], *r[1:]])
    elif what == "recipe gone":
        put("recipes", lambda r: r[1:])
    elif what == "document id":
        put("recipes", lambda r: first(r, doc_id=10**9))
    elif what == "manifest":
        put("manifest", lambda r: first(r, base=r[0]["base"] + 1))
    elif what == "store":
        put("store", lambda r: first(r, root=b"x" * 32))
    assert idstore.verify(spark, folder) == (what == "nothing")


def test_checksums_of_parts():
    rnd = random.Random(1)
    for _ in range(50):
        parts = [rnd.randbytes(4 * rnd.randint(0, 3000)) for _ in range(rnd.randint(1, 5))]
        after = np.cumsum([len(p) for p in parts][::-1])[::-1] - [len(p) for p in parts]
        got = np.bitwise_xor.reduce(idstore.shifted_crc(np.array([crc32(p) for p in parts], np.int64), after))
        assert got == crc32(b"".join(parts))


def fewest(items, capacity):
    best = [len(items)]

    def rec(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(items):
            best[0] = len(bins)
            return
        for j in {b: j for j, b in enumerate(bins) if b + items[i] <= capacity}.values():
            bins[j] += items[i]
            rec(i + 1, bins)
            bins[j] -= items[i]
        rec(i + 1, bins + [items[i]])

    items = sorted(items, reverse=True)
    rec(0, [])
    return best[0]


def test_packing_is_optimal_on_small_cases():
    rnd = random.Random(2)
    for n in range(300):
        capacity = rnd.choice([10, 20, 30, 100])
        items = [rnd.randint(1, capacity if n % 2 else capacity * 2 // 3) for _ in range(rnd.randint(1, 12))]
        best = packing.pack_lengths(dict(Counter(items)), capacity)
        patterns, least = best.patterns, fewest(items, capacity)
        assert best.bound <= least and (not best.proved or best.sequences == least)
        got = Counter()
        for p, times in patterns:
            assert sum(p) <= capacity
            got.update({x: k * times for x, k in Counter(p).items()})
        assert got == Counter(items) and sum(t for _, t in patterns) == fewest(items, capacity)


def test_packing_goes_on_after_the_first_exact_filling():
    best = packing.pack_lengths({50: 1, 49: 1, 48: 1, 32: 1, 30: 1, 25: 2, 21: 1, 20: 1}, 100)
    assert best.sequences == 3 and best.proved


def test_packing_bounds_and_time():
    import time

    assert packing.lower_bound({60: 5, 50: 2}, 100) == 6 and packing.lower_bound({51: 4, 49: 4}, 100) == 4 and packing.lower_bound({70: 3, 40: 3}, 100) == 5
    rnd = random.Random(6)
    began = time.process_time()
    many = dict(Counter(rnd.randint(1000, 2000) for _ in range(200)))
    best = packing.pack_lengths(many)
    first = sum(n for _, n in packing.best_fit_decreasing(many, 4096))
    assert best.bound <= best.sequences <= first and best.nodes <= packing.NODES and time.process_time() - began < 60


def test_packing_of_documents(docs, ids):
    got = packing.pack(docs).collect()
    for r in got:
        own = ids[r.doc_id][r.start : r.start + r.length]
        assert len(own) == r.length and crc32(own.tobytes()) == r.ids_crc32 and r.start == 4096 * r.piece
    assert sum(r.length for r in got) == sum(map(len, ids.values()))
    assert len({r.sequence_id for r in got}) <= -(-sum(map(len, ids.values())) // 4096) + 1


def test_cap_filters_find_the_links(spark):
    rng = np.random.default_rng(3)
    base = rng.standard_normal((300, 64))
    rows = [base]
    for cos in (0.999, 0.96, 0.94, 0.931, 0.92, 0.9):
        z = rng.standard_normal((300, 64))
        unit = base / np.linalg.norm(base, axis=1, keepdims=True)
        z -= (z * unit).sum(axis=1, keepdims=True) * unit
        z /= np.linalg.norm(z, axis=1, keepdims=True)
        rows.append((cos * unit + math.sqrt(1 - cos * cos) * z) * 3)
    v = np.vstack(rows).astype(np.float32)
    label = np.tile(np.arange(300) % 3, 7)
    df = spark.createDataFrame([(int(i), x.tolist(), int(c)) for i, (x, c) in enumerate(zip(v, label))], "vec_id long, embedding array<float>, label int")
    u = v.astype(float) / np.linalg.norm(v.astype(float), axis=1, keepdims=True)
    link = (u @ u.T >= 0.93) & (label[:, None] == label) & ~np.eye(len(v), dtype=bool)
    try:
        for block in (2048, 20):
            capfilters.BLOCK = block
            got = {r.vec_id: r for r in capfilters.near_vectors(df).collect()}
            found = np.array([got[i].n_links for i in range(len(v))])
            assert (found <= link.sum(axis=1)).all() and found.sum() >= 0.99 * link.sum()
    finally:
        capfilters.BLOCK = 2048


def test_url_rules_against_definition(spark):
    rnd = random.Random(4)
    hosts = ["com", "a.com", "b.a.com", "xa.com", "org", "a.org", "c.b.a.com", ""]
    paths = ["/", "/e", "/en/", "/en/7", "/en/78", "/fr/", ""]
    rules = list({(rnd.choice(hosts[:-1]), rnd.choice(paths)): rnd.choice(["allow", "block"]) for _ in range(14)}.items())
    pages = [(i, f"http://{rnd.choice(hosts)}{rnd.choice(paths)}{rnd.choice(['', '9', '?q', '#f'])}") for i in range(300)]
    got = urls.filter_urls(spark.createDataFrame(pages, "page_id long, url string"), spark.createDataFrame([(h, p, v) for (h, p), v in rules], "host string, path string, verdict string"))
    for r in got.collect():
        fit = [(len(h) + len(p), len(h), v, h + p) for (h, p), v in rules if (r.host == h or r.host.endswith("." + h)) and r.path.startswith(p)]
        assert (r.rule, r.verdict) == ((max(fit)[3], max(fit)[2]) if fit else (None, "allow"))


def test_chaining_finds_exact_and_fuzzy_passages(spark, docs, texts):
    rnd = random.Random(3)
    word = lambda: rnd.choice("abcdefghijklmnop") + rnd.choice("abcdefghij") + rnd.choice("xyzuvw") + str(rnd.randint(0, 9))
    w = lambda n: [word() for _ in range(n)]
    exact, base = w(60), w(80)
    fuzzy = list(base)
    for i in range(7, 80, 13):
        fuzzy[i] = "zz"
    fuzzy.insert(40, "qq")
    del fuzzy[61]
    rows = [(1, w(40) + exact + w(30)), (2, w(100) + exact + w(10)), (3, w(20) + base + w(20)), (4, w(33) + fuzzy + w(50)), (5, w(200)), (6, w(9) + exact[:30] + w(40))]
    got = {(r.doc_id, r.ref_doc_id): (r.start_word, r.end_word) for r in chaining.passages(spark.createDataFrame([(i, " ".join(x)) for i, x in rows], "doc_id long, text string")).collect()}
    assert got[2, 1] == (100, 160) and set(got) == {(2, 1), (4, 3)}
    assert got[4, 3][0] == 33 and got[4, 3][1] >= 33 + 55
    # every exact run of fifty words that a smaller id has too
    seen, hit, covered = {}, {}, {}
    for i in sorted(texts):
        words = texts[i].lower().split()
        grams = [tuple(words[j : j + 50]) for j in range(len(words) - 49)]
        for j, g in enumerate(grams):
            if seen.get(g, i) != i:
                hit.setdefault(i, set()).update(range(j, j + 50))
        for g in grams:
            seen.setdefault(g, i)
    for r in chaining.passages(docs).collect():
        covered.setdefault(r.doc_id, set()).update(range(r.start_word, r.end_word))
    assert set(hit) <= set(covered)
    assert sum(len(hit[i] & covered[i]) for i in hit) >= 0.99 * sum(map(len, hit.values()))


@pytest.mark.parametrize("copies", [1, 30])
def test_chaining_looks_beyond_first_occurrences(spark, copies):
    rnd = random.Random(9)
    w = lambda n: ["".join(rnd.choices("abcdefghij", k=6)) for _ in range(n)]
    rows, want = [], set()
    for _ in range(40 if copies == 1 else 4):
        whole, i = w(90), len(rows)
        # halves too short to be passages, then twice the whole
        rows += [(i + 2 * c + h, w(30) + whole[45 * h : 45 * h + 45] + w(30)) for c in range(copies) for h in (0, 1)]
        i = len(rows)
        rows += [(i, w(20) + whole + w(20)), (i + 1, w(25) + whole + w(9))]
        want.add((i + 1, i, 25, 115))
    got = chaining.passages(spark.createDataFrame([(i, " ".join(x)) for i, x in rows], "doc_id long, text string")).collect()
    assert {(r.doc_id, r.ref_doc_id, r.start_word, r.end_word) for r in got} == want


@pytest.mark.parametrize("changed, least", [(0.05, 0.99), (0.1, 0.98), (0.15, 0.9)])
def test_chaining_recall_by_changed_words(spark, changed, least):
    rnd = random.Random(12)
    w = lambda n: ["".join(rnd.choices("abcdefghij", k=6)) for _ in range(n)]
    rows = []
    for i in range(150):
        base = w(100)
        other = [rnd.choice("klmnop") * 5 + str(rnd.randint(0, 999)) if rnd.random() < changed else x for x in base]
        rows += [(2 * i, w(40) + base + w(40)), (2 * i + 1, w(55) + other + w(25))]
    got = {(r.doc_id, r.ref_doc_id) for r in chaining.passages(spark.createDataFrame([(i, " ".join(x)) for i, x in rows], "doc_id long, text string")).collect()}
    assert all(a == b + 1 and b % 2 == 0 for a, b in got)
    assert len(got) >= least * 150


def test_chaining_match_against_all_pairs():
    """Runs cut over batches at every place give the same matches; few occurrences all, many at least their first."""
    import pyarrow as pa

    rng = np.random.default_rng(13)
    size = [1, 2, 16, 17, 40, 3, 90, 5]
    key = np.repeat(np.arange(len(size)), size)
    rows = sorted((int(k), int(rng.integers(0, 2)), int(rng.integers(0, 2)), int(d), 7) for d, k in enumerate(key))
    same = 0x1111111111111111
    cols = [np.array(c) for c in zip(*rows)]
    names, kinds = ["key", "after", "long", "doc_id", "pos", "ref_id"], [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64()]

    def matches(step):
        out = set()
        full = [pa.array((c + same if n == "after" else c), k) for c, n, k in zip(cols, names, kinds)] + [pa.nulls(len(rows), pa.int64())]
        batches = [pa.RecordBatch.from_arrays([c[a : a + step] for c in full], names=names) for a in range(0, len(rows), step)]
        for b in chaining._match(batches):
            out.update(zip(b.column(0).to_pylist(), b.column(1).to_pylist()))
        return out

    got = matches(len(rows))
    assert all(matches(step) == got for step in (1, 3, 7, 20, 50))
    by = {}
    for r in rows:
        by.setdefault(r[0], []).append(r[3])
    for k, docs in by.items():
        if len(docs) <= chaining.MANY:
            assert {(max(a, b), min(a, b)) for a in docs for b in docs if a != b} <= got
        else:
            assert all(any(d in pair for pair in got) for d in docs)


def test_chaining_of_what_very_many_documents_share(spark):
    """A passage of 400 documents, a line of all of them, and stretches of two words over and over."""
    rnd = random.Random(16)
    w = lambda n: ["".join(rnd.choices("abcdefghij", k=6)) for _ in range(n)]
    passage, short = w(80), w(14)
    rows = [(i, w(30) + short + (w(20) + passage + w(9) if i % 2 else w(60))) for i in range(800)]
    rows += [(2000 + i, w(30) + ["so", "on"] * 200 + w(10)) for i in range(60)]
    got = chaining.passages(spark.createDataFrame([(i, " ".join(x)) for i, x in rows], "doc_id long, text string").repartition(3)).collect()
    assert all(r.ref_doc_id < r.doc_id for r in got)
    covered = {}
    for r in got:
        covered.setdefault(r.doc_id, set()).update(range(r.start_word, r.end_word))
    assert set(covered) == {i for i, _ in rows if (i % 2 and 1 < i < 800) or i > 2000}
    assert all(covered[i] >= set(range(64, 144)) for i in range(3, 800, 2))
    assert all(len(covered[2000 + i] & set(range(30, 430))) >= 390 for i in range(1, 60))


def test_chains_of_scattered_anchors():
    p, q = [0, 10, 12, 20, 30, 500, 510], [5, 15, 290, 25, 36, 1800, 1810]
    chains = chaining.chain_anchors(p, q)
    assert chains == [[0, 1, 3, 4], [2], [5, 6]]  # what is left over is a chain of its own


def test_mixing_targets_by_resharing(spark, docs):
    got = mixing.mix(docs.select("doc_id", "source", "text")).collect()
    sizes, taken, target, big = Counter(), Counter(), {}, Counter()
    for r in got:
        assert r.mix_size == len([x for x in r.text.encode().split()])
        sizes[r.source] += r.mix_size
        taken[r.source] += r.mix_copies * r.mix_size
        target[r.source] = r.mix_target
        big[r.source] = max(big[r.source], r.mix_size)
    weight = {s: [3, 1, 2][i % 3] for i, s in enumerate(sorted(sizes))}
    want, left, free = dict.fromkeys(sizes, 0.0), 1.5 * sum(sizes.values()), set(sizes)
    while left > 1e-6:
        share = left / sum(weight[s] for s in free)
        left = 0.0
        for s in list(free):
            want[s] += share * weight[s]
            if want[s] > 2 * sizes[s]:
                left += want[s] - 2 * sizes[s]
                want[s] = 2 * sizes[s]
                free.discard(s)
    for s in sizes:
        assert abs(target[s] - want[s]) < 1e-3 and abs(taken[s] - want[s]) <= big[s]
    assert sorted(map(tuple, got)) == sorted(map(tuple, mixing.mix(docs.select("doc_id", "source", "text")).collect()))


def test_mixing_odds_by_size(spark):
    """Over many seeds a document is taken as often as its odds say, no source misses its target by more than a document."""
    rnd = random.Random(17)
    rows = [(i, rnd.choice("ab"), " ".join(["w"] * rnd.choice([3, 20, 100]))) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string").cache()
    seeds, copies = 12, Counter()
    for seed in range(seeds):
        got = mixing.mix(df, cycle=(1, 1), share=0.7, seed=seed, odds="size").collect()
        taken, target = Counter(), {}
        for r in got:
            copies[r.source, r.mix_size] += r.mix_copies
            taken[r.source] += r.mix_copies * r.mix_size
            target[r.source] = r.mix_target
        assert all(abs(taken[s] - target[s]) <= 100 for s in target)
    many = Counter((s, len(t.split())) for _, s, t in rows)
    for s in "ab":
        g = {x: (x + 1).bit_length() for x in (3, 20, 100)}
        rate = target[s] / sum(g[x] * x * many[s, x] for x in g)
        for x in g:
            want = min(2, rate * g[x])
            assert abs(copies[s, x] / seeds / many[s, x] - want) < 0.12, (s, x, want)
    w = mixing.mix(df.withColumn("w", F.col("doc_id") % 3), share=0.5, cycle=(1, 1), odds="w").collect()
    assert all(r.mix_copies == 0 for r in w if r.doc_id % 3 == 0) and any(r.mix_copies == 2 or r.mix_copies == 1 for r in w)


def test_language_and_quality_held_out(spark):
    got = langid.op7_langid(spark, D).join(spark.read.parquet(f"{D}/documents.parquet").select("doc_id", "lang"), "doc_id").filter("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in got) >= 0.98 * len(got) and not any(r.rejected for r in got)
    got = quality.op9_quality(spark, D).join(spark.read.parquet(f"{D}/labels.parquet"), "doc_id").filter("held_out").collect()
    assert sum(r.predicted == r.quality for r in got) >= 0.93 * len(got)


def test_language_rejects_noise_and_unlearned_languages(spark, docs):
    model, rnd = langid.train(docs), random.Random(10)
    finnish = "Kaikki ihmiset syntyvät vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan. Heille on annettu järki ja omatunto, ja heidän on toimittava toisiaan kohtaan veljeyden hengessä. " * 3
    letters = " ".join("".join(rnd.choices("abcdefghijklmnopqrstuvwxyz", k=rnd.randint(2, 9))) for _ in range(200))
    base64 = "".join(rnd.choices("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", k=900))
    rows = [(1, finnish), (2, letters), (3, base64), (4, "x 1 22 333 " * 60)]
    got = langid.identify(spark.createDataFrame(rows, "doc_id long, text string"), model).collect()
    assert all(r.rejected for r in got), [(r.doc_id, r.distance) for r in got]
    assert sum(r.rejected for r in langid.identify(docs, model).collect()) <= 0.01 * docs.count()


def test_gram_counts():
    t = [b"", b"a", b"abcab", b"zz" * 700_000]
    got = gram_counts(t, (1, 3), 64)
    assert got.sum(axis=1).tolist() == [0, 1, 5 + 3, 1_400_000 + 1_399_998] or got[:3].sum(axis=1).tolist() == [0, 1, 8]


def test_topk_ties(spark):
    rng = np.random.default_rng(6)
    v = rng.integers(-2, 3, (250, 5)).astype(float) / 4
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<float>")
    f = np.floor(v * 1024).astype(int)
    got = {}
    for r in topk.top_k(df, df.filter("vec_id % 100 = 0"), 7).collect():
        got.setdefault(r.query_id, {})[r.rank] = (r.vec_id, r.score)
    for q in (0, 100, 200):
        s = sorted((-int(f[q] @ f[j]), j) for j in range(250) if j != q)[:7]
        assert [got[q][n + 1] for n in range(7)] == [(j, -x) for x, j in s]


def test_fingerprints_and_components(spark, docs, texts):
    rows = simhash.near_texts(docs).collect()
    fp = {r.doc_id: r.fp0 & (2**64 - 1) for r in rows}
    for i, t in list(texts.items())[:60]:
        words = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t).split()
        grams = [" ".join(words)] if len(words) < 4 else [" ".join(words[j : j + 4]) for j in range(len(words) - 3)]
        h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
        assert fp[i] == sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    keys = sorted(fp)
    f = np.array([fp[i] for i in keys], np.uint64)
    near, comp = np.bitwise_count(f[:, None] ^ f) <= 4, np.array(keys)
    while True:
        new = np.array([comp[n].min() for n in near])
        if (new == comp).all():
            break
        comp = new
    assert {r.doc_id: r.component_id for r in rows} == dict(zip(keys, comp.tolist()))


@pytest.mark.parametrize("many, block", [(2, 8192), (3, 40), (4, 8192)])
def test_multi_index_misses_nothing(spark, many, block):
    rng = np.random.default_rng(7)
    base = rng.integers(0, 2**63, 200, dtype=np.uint64)
    sets = [base] + [base[:100] ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, (r, 100), dtype=np.uint64), axis=0) for r in (1, 2, 3, 4, 4, 5, 6)]
    f = np.unique(np.concatenate([*sets, base[0] ^ (np.uint64(1) << np.arange(64, dtype=np.uint64))]))
    near, comp = np.bitwise_count(f[:, None] ^ f) <= 4, f.view(np.int64)
    while True:
        new = np.array([comp[n].min() for n in near])
        if (new == comp).all():
            break
        comp = new
    old, simhash.BLOCK = simhash.BLOCK, block
    try:
        got = {r.id: r.root for r in simhash.link_fingerprints(spark.createDataFrame([(int(x), int(x)) for x in f.view(np.int64)], "id long, fp0 long"), 4, many).collect()}
    finally:
        simhash.BLOCK = old
    assert all(got.get(int(x), int(x)) == int(c) for x, c in zip(f.view(np.int64), comp))


@pytest.mark.parametrize("rows", [10**5, 10**6, 10**7, 10**8, 10**9, 10**10])
def test_wide_segments_keep_their_recall_at_every_size(rows):
    rng = np.random.default_rng(rows)
    plan = simhash.wide_segments(2, rows)
    for differ, least in ((12, 0.99), (19, 0.95)):
        a = rng.integers(0, 2**63, (2000, 2), dtype=np.uint64)
        b = a.copy()
        for i in range(len(b)):
            for x in rng.choice(128, differ, replace=False):
                b[i, x // 64] ^= np.uint64(1) << np.uint64(x % 64)
        met = np.zeros(len(a), bool)
        for bits, ball in plan:
            x, y = (simhash._value(list(f.T), bits) for f in (a, b))
            met |= np.bitwise_count(x ^ y) <= ball
        assert met.mean() >= least, (rows, differ, met.mean(), len(plan))


def test_near_texts_of_the_pipeline_against_all_pairs(spark):
    rnd = random.Random(14)
    w = lambda n: ["".join(rnd.choices("abcdefghij", k=5)) for _ in range(n)]
    rows = []
    for g in range(60):
        base = w(rnd.randint(80, 300))
        for changed in (0, 0.01, 0.02, 0.03, 0.05, 0.08):
            rows.append([x if rnd.random() >= changed else "zz" + str(rnd.randint(0, 9999)) for x in base])
    hub = w(200)  # many near copies of one text
    rows += [[x if j not in (i % 190, (i * 7) % 190) else f"q{i}" for j, x in enumerate(hub)] for i in range(300)]
    rnd.shuffle(rows)
    texts = {i: " ".join(x) for i, x in enumerate(rows)}
    sets = [frozenset(" ".join(x[j : j + 5]) for j in range(len(x) - 4)) for x in rows]
    comp = list(range(len(rows)))
    where = {}
    for i, s in enumerate(sets):
        for g in s:
            where.setdefault(g, []).append(i)
    pairs = {(a, b) for d in where.values() for a in d for b in d if a < b}
    links = [(a, b) for a, b in pairs if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]

    def find(x):
        while comp[x] != x:
            x = comp[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        comp[b] = a
    want = {i for i in range(len(rows)) if find(i) == i}
    got = {r.doc_id for r in simhash.keep_one(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert want <= got  # what is not alike to 0.8 stays
    assert len(got - want) <= 0.02 * (len(rows) - len(want))  # near copies go


def test_forest_is_least_and_spans():
    rng = np.random.default_rng(15)
    for _ in range(50):
        n, m = int(rng.integers(2, 30)), int(rng.integers(1, 80))
        i, j, d = rng.integers(0, n, m), rng.integers(0, n, m), rng.integers(0, 5, m)
        i, j, d = i[i != j], j[i != j], d[i != j]
        keep = simhash._forest(i, j, d, n)
        comp, cost = list(range(n)), 0
        find = lambda x: x if comp[x] == x else find(comp[x])
        for e in np.argsort(d, kind="stable"):
            a, b = find(i[e]), find(j[e])
            if a != b:
                comp[a], cost = b, cost + d[e]
        assert d[keep].sum() == cost and len(keep) == n - len({find(x) for x in range(n)})


def test_components_of_long_paths(spark):
    rnd = random.Random(8)
    names = list(range(60))
    rnd.shuffle(names)
    edges = [(names[i], names[i + 1]) for i in range(39)] + [(names[50], names[51]), (names[55], names[55]), (None, 3)]
    got = {r.id: r.root for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{n: min(names[:40]) for n in names[:40]}, **{n: min(names[50:52]) for n in names[50:52]}}


def test_topk_phases_hold_only_entries_over_the_threshold(spark):
    rng = np.random.default_rng(11)
    centre = rng.standard_normal((20, 16))
    v = np.vstack([centre[i % 20] + 0.2 * rng.standard_normal(16) for i in range(900)] + [centre[0]] * 300)  # a hot vector
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(v)], "vec_id long, embedding array<double>").repartition(3)
    f = np.floor(v * 1024).astype(int)
    got, parts = topk.search(df, df.filter("vec_id % 100 = 0"), 10)
    best = {}
    for r in got.collect():
        best.setdefault(r.query_id, {})[r.rank] = (r.vec_id, r.score)
    for q in range(0, 1200, 100):
        s = sorted((-int(f[q] @ f[j]), j) for j in range(1200) if j != q)[:10]
        assert [best[q][n + 1] for n in range(10)] == [(j, -x) for x, j in s]
    assert parts["nodes"].count() == 901 and parts["nodes"].selectExpr("max(size(ids))").first()[0] == 11
    over = parts["over"].collect()
    asked = 901 * len({r.q for r in over})
    u = np.unique(f, axis=0)
    tau = {r.q: r.tau for r in parts["cutoffs"].collect()}
    assert all(t <= sorted((u @ f[q]).tolist())[-11] for q, t in tau.items())  # no cutoff is above the true one
    assert all(r.part >= tau[r.q] / topk.LISTS - 1e-3 for r in over)
    assert len(over) < topk.LISTS * asked / 4  # a small part of all partial scores
    resolved = {(r.q, r.node) for r in parts["missing"].collect()}
    sent = Counter((r.q, r.node) for r in over)
    assert resolved == {p for p, n in sent.items() if n < topk.LISTS}


def test_topk_of_repeated_query_ids(spark):
    rows = [(100, [1.0, 0.0]), (100, [0.0, 1.0]), (1, [2.0, 0.0]), (2, [0.0, 3.0]), (2, [0.0, 3.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = topk.top_k(df, df.filter("vec_id = 100"), 3).orderBy("rank").collect()
    assert [(r.vec_id, r.score) for r in got] == [(2, 3 << 20), (2, 3 << 20), (1, 0)]  # (0, 1) is the least vector


def _plain_grams(text, orders, buckets, letters=None):
    """Hashed byte n-grams one by one."""
    data = [letters[b] for b in text] if letters is not None else list(text)
    out = Counter()
    for n in orders:
        for i in range(len(data) - n + 1):
            code = 0
            for b in data[i : i + n]:
                code = (code * 257 + b) % 2**32
            out[((code + n) * 2654435761 % 2**32 >> 16) % buckets] += 1
    return out


def test_language_against_a_plain_nearest_centroid(spark, docs, texts):
    model = langid.train(docs)
    some = {i: texts[i] for i in sorted(texts)[:40] if texts[i] and any(map(str.isalpha, texts[i])) and len(texts[i]) < 4000}
    got = {r.doc_id: r for r in langid.identify(docs, model).collect()}
    stays = {r.doc_id for r in langid.keep_identified(docs, model).collect()}
    assert stays == {i for i, r in got.items() if not r.rejected}
    letters = langid._LETTERS.tolist()
    for i, t in some.items():
        x = {b: math.log1p(n) * float(model.idf[b]) for b, n in _plain_grams(t.lower().encode(), (1, 2, 3), langid.BUCKETS, letters).items()}
        norm = math.sqrt(sum(v * v for v in x.values()))
        cos = [sum(v * float(c[b]) for b, v in x.items()) / norm for c in model.centroids]
        best = max(range(len(cos)), key=lambda j: cos[j])
        assert abs(got[i].score - min(1, max(0, cos[best]))) < 1e-4
        assert got[i].lang_pred == model.names[best] or sorted(cos)[-1] - sorted(cos)[-2] < 1e-5
        assert got[i].rejected == (1 - cos[best] > model.limit[best]) or abs(1 - cos[best] - model.limit[best]) < 1e-4


def test_quality_against_a_plain_network(spark, docs, texts):
    labels = spark.read.parquet(f"{D}/labels.parquet")
    model = quality.train(docs, labels)
    net = model.net
    got = {r.doc_id: r.score for r in quality.score(docs, model).collect()}
    for i in [i for i in sorted(texts) if len(texts[i] or "") < 3000][:25]:
        t = (texts[i] or "").encode()
        words = [crc32(w) % quality.WORDS for w in t.split()]
        grams = _plain_grams(t, (3,), quality.GRAMS)
        mean = lambda rows, n: [sum(c) / max(n, 1) for c in zip(*rows)] if rows else [0.0] * quality.DIM
        x = [*mean([model.vectors[b].tolist() for b in words], len(words)), *mean([quality.INDEX[b].tolist() for b in words], len(words)), *mean([(quality.GRAM_INDEX[b] * n).tolist() for b, n in grams.items()], sum(grams.values()))]
        a = [(v - m) / s for v, m, s in zip(x, net.mean, net.scale)]
        h = [math.tanh(sum(p * q for p, q in zip(a, col)) + b) for col, b in zip(net.w1.T.tolist(), net.b1.tolist())]
        z = (sum(p * q for p, q in zip(h, net.w2.tolist())) + net.b2) / net.temperature
        assert abs(got[i] - 1 / (1 + math.exp(-max(-50, min(50, z))))) < 1e-3


def test_temperature_calibrates():
    rng = np.random.default_rng(18)
    x = rng.standard_normal((3000, 6))
    y = (rng.random(3000) < 1 / (1 + np.exp(-1.5 * x[:, 0]))).astype(float)
    net = quality.fit(x, y)
    aside = np.arange(len(x)) % 5 == 0
    z = net.logits(x[aside])
    loss = lambda t: float(np.mean(np.logaddexp(0, z / t) - y[aside] * z / t))
    assert all(loss(net.temperature) <= loss(t) + 1e-9 for t in (0.25, 0.5, 1, 2, 4, 8))
    p = net.score(rng_x := rng.standard_normal((4000, 6)))
    truth = 1 / (1 + np.exp(-1.5 * rng_x[:, 0]))
    for lo in (0.1, 0.4, 0.7):
        at = (p >= lo) & (p < lo + 0.2)
        assert abs(p[at].mean() - truth[at].mean()) < 0.08


def test_cut_passages_against_their_spans(spark, docs, texts):
    gone = {}
    for r in chaining.passages(docs).collect():
        gone.setdefault(r.doc_id, set()).update(range(r.start_word, r.end_word))
    left = {r.doc_id: r.text for r in chaining.cut_passages(docs).collect()}
    for i, t in texts.items():
        words = (t or "").encode().split()
        stay = [w.decode() for n, w in enumerate(words) if n not in gone.get(i, ())]
        if i not in gone:
            assert left[i] == t
        elif stay:
            assert [w.decode() for w in left[i].encode().split()] == stay
        else:
            assert i not in left
