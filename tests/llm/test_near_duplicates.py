import random
import re

import pytest

from tabletext.llm import near_duplicates as nd

from .conftest import corpus

AZ = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(text, k):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(AZ))
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()


def brute(texts, k):
    sets = [shingles(t, k) for t in texts]
    label = list(range(len(texts)))

    def root(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(len(sets)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((root(i), root(j)))
                label[b] = a
    return {i: (len(s), root(i)) for i, s in enumerate(sets)}


def mutated(seed, n):
    """A family of near copies of one text, some too far from it but near each other."""
    r = random.Random(seed)
    base = [f"w{r.randrange(400)}" for _ in range(120)]
    out = []
    for _ in range(n):
        own = list(base)
        for _ in range(r.choice([0, 1, 3, 6, 8, 9, 10, 14])):
            own[r.randrange(len(own))] = f"x{r.randrange(9)}"
        out.append(" ".join(own))
    return out


@pytest.mark.parametrize("k", [2, 5])
def test_components_are_those_of_brute_force(frame, k):
    texts = corpus() + mutated(1, 60) + mutated(2, 25)
    found = nd.near_duplicate_classes(frame(texts), words=k).collect()
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in found} == brute(texts, k)


def test_blocks_smaller_than_buckets(frame, monkeypatch):
    monkeypatch.setattr(nd, "BLOCK", 3)
    texts = mutated(5, 60)
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in nd.near_duplicate_classes(frame(texts), words=2).collect()} == brute(texts, 2)


def test_long_chain_of_components(spark):
    n = 300
    order = list(range(n))
    random.Random(3).shuffle(order)
    edges = [(order[i], order[i + 1]) for i in range(n - 1)] + [(1000, 1001), (1001, 1002), (1003, 1002)]
    got = {r["node"]: r["label"] for r in nd.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 0 for i in range(n)}, **{i: 1000 for i in range(1000, 1004)}}


def test_odd_rows(spark, frame):
    assert nd.op8(frame([])).count() == 0
    rows = {r["doc_id"]: r for r in nd.op8(frame([None, "", "word", "word", "WORD"])).collect()}
    assert [rows[i]["component_id"] for i in range(5)] == [0, 1, 2, 2, 2]
    docs = frame([(4, "a b c d e f g"), (2, "a b c d e f g"), (9, None)])
    assert {r["doc_id"] for r in nd.drop_near_duplicates(docs).collect()} == {2, 9}


def test_null_ids_and_column_names(frame):
    """A null id stays beside others; columns may have any names."""
    text = "one two three four five six seven eight nine ten eleven twelve"
    docs = frame([(None, text), (5, text), (3, text + " thirteen"), (None, "alone"), (9, None)]).selectExpr("*", "1 as __gone", "2 as node", "3 as component_id")
    got = {(r["doc_id"], r["component_id"], r["kept"]) for r in nd.op8(docs).collect()}
    assert got == {(None, 3, False), (5, 3, False), (3, 3, True), (None, None, True), (9, 9, True)}
    kept = nd.drop_near_duplicates(docs, words=2)
    assert kept.columns == docs.columns and sorted(str(r["doc_id"]) for r in kept.collect()) == ["3", "9", "None", "None"]


def test_minima_estimate_similarity():
    """Shares of equal minima are near the similarity of the sets, as for hashes drawn from a universal family."""
    import numpy as np

    r = np.random.default_rng(0)
    pool = r.integers(0, 1 << 64, 3000, dtype=np.uint64)
    for share in (0.2, 0.5, 0.8):
        own = int(1000 * share)
        seen = []
        for i in range(20):
            p = r.permutation(pool)
            a, b = np.sort(p[:1000]), np.sort(np.concatenate([p[:own], p[1000 : 2000 - own]]))
            x, y = nd.signatures([a, b])
            seen.append((x == y).mean())
        assert abs(np.mean(seen) - own / (2000 - own)) < 0.03
