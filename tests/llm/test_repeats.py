import hashlib
import re
from collections import Counter

import numpy as np
import pytest

from tabletext.llm import anchors, substring_dedup, suffix_dedup

from .conftest import corpus


def brute_bytes(rows, length):
    seen = Counter()
    texts = [(i, (t or "").encode()) for i, t in rows]
    for _, t in texts:
        seen.update(t[i : i + length] for i in range(len(t) - length + 1))
    out = []
    for i, t in texts:
        gone = [False] * len(t)
        for a in range(len(t) - length + 1):
            if seen[t[a : a + length]] > 1:
                gone[a : a + length] = [True] * length
        kept = bytes(b for b, g in zip(t, gone) if not g)
        runs = sum(g and not (j and gone[j - 1]) for j, g in enumerate(gone))
        out.append((i, len(t), sum(gone), runs, hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def brute_words(rows, length):
    rows = [(i, re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t in rows]
    first = {}
    order = lambda i: -1 if i is None else i
    for i, w in rows:
        for a in range(len(w) - length + 1):
            key = tuple(w[a : a + length])
            first[key] = min(first.get(key, order(i)), order(i))
    out = []
    for i, w in rows:
        gone = [False] * len(w)
        for a in range(len(w) - length + 1):
            if first[tuple(w[a : a + length])] < order(i):
                gone[a : a + length] = [True] * length
        kept = " ".join(x for x, g in zip(w, gone) if not g)
        out.append((i, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()))
    return sorted(out, key=str)


ODD = [(3, "same id other text " * 20), (None, "null id " * 60), (None, "null id " * 60), (0, "same id other text " * 20), (500, "null id " * 60)]


@pytest.mark.parametrize(("seed", "odd", "hot"), [(1, [], None), (2, ODD, None), (3, [], 1)])
def test_bytes_against_brute_force(frame, monkeypatch, seed, odd, hot):
    if hot is not None:
        monkeypatch.setattr(anchors, "HOT", hot)
    rows = list(enumerate(corpus(seed))) + odd
    for length in (200, 40):
        got = sorted((tuple(r) for r in suffix_dedup.removal_report(frame(rows), length).collect()), key=str)
        assert got == brute_bytes(rows, length)


@pytest.mark.parametrize(("seed", "odd", "hot"), [(1, [], None), (2, ODD, None), (3, [], 1)])
def test_words_against_brute_force(frame, monkeypatch, seed, odd, hot):
    if hot is not None:
        monkeypatch.setattr(anchors, "HOT", hot)
    rows = list(enumerate(corpus(seed))) + odd
    for length in (13, 5):
        got = sorted((tuple(r) for r in substring_dedup.removal_report(frame(rows), length).collect()), key=str)
        assert got == brute_words(rows, length)


def test_interval_tree_on_a_small_array():
    # common prefixes 1 3 0 0 2 are those of the suffixes of "banana"
    assert sorted(suffix_dedup.intervals([1, 3, 0, 0, 2], 1)) == [(0, 3, 1), (1, 3, 3), (4, 6, 2)]


def test_left_diversity():
    before, after = [b"xq", b"yq", b"zq"], [b"abcd", b"abce", b"abzz"]
    node, member, left, depth, diverse = suffix_dedup.repeats(before, after, 4, 2)
    rows = {(d, m): (e, v) for d, m, e, v in zip(depth.tolist(), member.tolist(), left.tolist(), diverse.tolist())}
    assert rows == {(3, 0): (1, False), (3, 1): (1, False), (2, 0): (1, False), (2, 1): (1, False), (2, 2): (1, False)}


def test_wavelet_tree_ranks():
    r = np.random.default_rng(1)
    symbols = r.integers(0, 37, 1000)
    tree = substring_dedup.WaveletTree(symbols, 37)
    places, wanted = r.integers(0, 1001, 500), r.integers(0, 37, 500)
    assert tree.rank(wanted, places).tolist() == [int((symbols[:p] == s).sum()) for p, s in zip(places, wanted)]


def test_remove_keeps_columns_and_valid_text(frame):
    shared = "gemeinsamer Absatz über Brücken und Wörter, " * 8
    docs = frame(["eins é " + shared + "ü ende", "zwei è " + shared + "ä schluss", None, ""])
    rows = suffix_dedup.remove_repeats(docs).orderBy("doc_id").collect()
    assert list(rows[0].asDict()) == docs.columns and rows[0]["text"].startswith("eins") and rows[0]["n_chars"] == len(rows[0]["text"]) < 30
    assert rows[2]["text"] is None and rows[3]["text"] == ""
    assert {(r["doc_id"], r["stop"] - r["start"] >= 200) for r in suffix_dedup.removed_runs(docs).collect()} == {(0, True), (1, True)}


def test_index_finds_the_string_of_each_suffix():
    r = np.random.default_rng(3)
    strings = [r.integers(1, 9, n) for n in r.integers(0, 30, 60)]
    symbols = np.concatenate([np.append(x, 0) for x in strings])
    owner = np.repeat(np.arange(60), [len(x) + 1 for x in strings])
    index = substring_dedup.FMIndex(symbols, owner, 60, 30)
    suffixes = sorted(range(len(symbols)), key=lambda i: [(x, 0) if x else (0, owner[j]) for j, x in enumerate(symbols[i:].tolist(), i)][: 30])
    inside = [i for i, at in enumerate(suffixes) if symbols[at]]
    assert index.strings_of(np.array(inside)).tolist() == [owner[suffixes[i]] for i in inside]


@pytest.mark.parametrize("seed", [1, 5])
def test_groups_hold_all_occurrences(frame, seed):
    """Members of a group are equal; every repeated window is in groups that hold all places it is at."""
    length = 40
    # periodic texts shorter: each place in them is in a group of all others
    rows = [(i, t if len(set(t or "")) > 4 else (t or "")[:140]) for i, t in enumerate(corpus(seed, 30))]
    texts = {i: (t or "").encode() for i, t in rows}
    groups = {}
    for g in suffix_dedup.repeat_groups(frame(rows), length).collect():
        groups.setdefault(g["group"], set()).add((g["doc_id"], g["start"], g["stop"]))
    where = {}
    for name, places in groups.items():
        assert len(places) > 1 and len({texts[d][a:b] for d, a, b in places}) == 1
        for d, a, b in places:
            if b - a >= length:
                for at in range(a, b - length + 1):
                    where.setdefault((d, at), []).append((name, at - a))
    seen = {}
    for d, t in texts.items():
        for at in range(len(t) - length + 1):
            seen.setdefault(t[at : at + length], set()).add((d, at))
    for places in seen.values():
        if len(places) > 1:
            for d, at in places:
                found = {(x, a + by) for name, by in where.get((d, at), []) for x, a, b in groups[name]}
                assert places <= found


def test_any_column_names(frame):
    """Columns may have the names that the search uses; repeated rows and null ids are kept."""
    shared = "the same passage of words that comes again and again in both of these texts, " * 4
    docs = frame([(1, "a " + shared), (2, "b " + shared), (None, "short"), (1, "a " + shared)])
    odd = docs.selectExpr("doc_id", "text as text", "1 as __id", "2 as __sum", "array(3) as __starts", "4 as __stops", "5 as column_0", "6 as `a.b`")
    for module in (suffix_dedup, substring_dedup):
        got = module.remove_repeats(odd)
        assert got.columns == odd.columns and got.count() == 4
        assert all(tuple(r)[2:] == (1, 2, [3], 4, 5, 6) for r in got.collect())


def test_texts_longer_than_a_block(frame):
    long = "".join(f"word{i} " for i in range(250_000))
    rows = [(0, long), (1, long[500_000:502_000] + " tail"), (2, "x" * 3_000_000)]
    got = sorted((tuple(r) for r in suffix_dedup.op6(frame(rows)).collect()), key=str)
    assert got[0][2:4] == (2000, 1) and got[1][2:4] == (2000, 1) and got[2][2:4] == (3_000_000, 1)
    words = sorted((tuple(r) for r in substring_dedup.op7(frame(rows)).collect()), key=str)
    assert words[0][1:3] == (250_000, 0) and words[1][2] > 150 and words[2][1:3] == (1, 0)


def test_empty(frame):
    assert suffix_dedup.op6(frame([])).count() == 0
    assert substring_dedup.op7(frame([])).count() == 0
