"""Links of near texts that a least forest of candidates passes over."""

import random
from itertools import combinations

import numpy as np
import pytest

from aggnear.llm import simhash


@pytest.mark.parametrize("block", [simhash.BLOCK, 24])
def test_no_candidate_between_unconnected_texts_is_passed_over(spark, monkeypatch, block):
    """Variants of one text that are alike to about 0.8: nearest fingerprints often fail where a farther one is alike."""
    monkeypatch.setattr(simhash, "BLOCK", block)
    rnd = random.Random(31)
    base = [rnd.randrange(10**6) for _ in range(400)]
    texts = {}
    for i in range(120):
        words = list(base)
        for at in rnd.sample(range(400), rnd.choice([5, 6, 7])):
            words[at] = rnd.randrange(10**6)
        texts[i] = " ".join(map(str, words))
    sets = {i: simhash.shingle_set(t.encode(), simhash.NEAR_SHINGLE) for i, t in texts.items()}
    fp = {i: np.array(simhash.fingerprint(t.encode(), simhash.NEAR_SHINGLE, simhash.WIDE), np.uint64) for i, t in texts.items()}
    plan = simhash.wide_segments(simhash.WIDE, len(texts))
    comp = list(range(len(texts)))

    def find(x):
        return x if comp[x] == x else find(comp[x])

    for a, b in combinations(texts, 2):
        far = fp[a] ^ fp[b]
        bits = [int(far[p // 64]) >> (p % 64) & 1 for p in range(64 * simhash.WIDE)]
        meet = any(sum(bits[p] for p in at) <= 1 for at, _ in plan)
        both = len(np.intersect1d(sets[a], sets[b]))
        if meet and sum(bits) <= simhash.WIDE_RADIUS and both >= simhash.ALIKE * (len(sets[a]) + len(sets[b]) - both):
            a, b = sorted((find(a), find(b)))
            comp[b] = a
    want = {i for i in texts if find(i) == i}
    assert 1 < len(want) < len(texts)
    got = {r.doc_id for r in simhash.keep_one(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()}
    assert got == want
