import hashlib
import re

import pytest

from tabletext.llm import decontamination as d

from .conftest import corpus

AZ = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(AZ))


def brute(texts, items, width=10):
    windows = {}
    for item, text in items:
        w = words(text)
        for i in range(len(w) - min(width, len(w)) + 1 if w else 0):
            windows.setdefault(tuple(w[i : i + min(width, len(w))]), set()).add(str(item))
    out = {}
    for k, text in enumerate(texts):
        w, hit, found = words(text), set(), set()
        for n in {len(x) for x in windows}:
            for i in range(len(w) - n + 1):
                if own := windows.get(tuple(w[i : i + n])):
                    hit |= set(range(i, i + n))
                    found |= own
        out[k] = (len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit))
    return out


@pytest.mark.parametrize("limit", [d.MAX_TEST_BYTES, 700])
def test_against_brute_force(spark, frame, limit):
    texts = corpus()
    parts = [t.split(" ") for t in texts if t and len(t.split(" ")) > 40]
    items = [(i, " ".join(p[5 : 5 + n])) for i, (p, n) in enumerate(zip(parts, [12, 10, 30, 9, 3, 1, 25, 11] * 2))]
    items += [(90, ""), (91, None), (92, "nowhere to be found in any of the training texts at all"), (93, items[0][1]), (94, "GAM ma")]
    table = spark.createDataFrame(items, "item_id long, text string")
    docs = frame(texts)
    report = d.with_hits(docs, table, max_test_bytes=limit)
    expected = brute(texts, items)
    got = d.op10(docs, table) if limit == d.MAX_TEST_BYTES else None
    if got is not None:
        assert {r["doc_id"]: tuple(r)[1:] for r in got.collect()} == expected
    assert {r["doc_id"]: (r[d.COUNT], len(r[d.ITEMS])) for r in report.collect()} == {k: (v[0], v[2]) for k, v in expected.items()}
    kept = d.decontaminate(docs, table, max_test_bytes=limit)
    assert kept.columns == docs.columns and {r["doc_id"] for r in kept.collect()} == {k for k, v in expected.items() if not v[4]}


def test_empty_sides(spark, frame):
    none = spark.createDataFrame([], "item_id long, text string")
    assert d.op10(frame([]), none).count() == 0
    assert not d.op10(frame(["some text"]), none).first()["contaminated"]


def brute_matches(texts, items, least):
    """Every maximal run of equal words, from all pairs of places."""
    out = set()
    for item, text in items:
        a = words(text)
        for doc, other in enumerate(texts):
            b = words(other)
            for i in range(len(a)):
                for j in range(len(b)):
                    if a[i] == b[j] and not (i and j and a[i - 1] == b[j - 1]):
                        n = 0
                        while i + n < len(a) and j + n < len(b) and a[i + n] == b[j + n]:
                            n += 1
                        if n >= least:
                            out.add((str(item), i, doc, j, n))
    return out


@pytest.mark.parametrize("limit", [d.MAX_TEST_BYTES, 300])
def test_matches_and_their_places(spark, frame, limit):
    texts = ["a b c d e f g h i j k l m n", "x a b c d e q e f g h i j k", None, "", "to to to to to", "k l m n a b c d e f g h i j k l m n o p"]
    items = [(1, "a b c d e f g h i j k l m n"), (2, "to to to"), (3, "zz e f g h i j k yy"), (4, None), (5, "n a b c")]
    table = spark.createDataFrame(items, "item_id long, text string")
    for least in (2, 4, 11):
        got = [tuple(r) for r in d.verbatim_matches(frame(texts), table, least, max_test_bytes=limit).collect()]
        want = brute_matches(texts, items, least)
        assert len(got) == len(set(got)) and set(got) == want
        longest = {}
        for item, i, doc, j, n in want:
            for by in range(n - least + 1):
                key, own = (item, i + by), (-(n - by), doc, j + by)
                longest[key] = min(longest.get(key, own), own)
        found = {(r[0], r[1]): (-r[2], r[3], r[4]) for r in d.longest_matches(frame(texts), table, least, max_test_bytes=limit).collect()}
        assert found == longest


def test_odd_items_and_names(spark, frame):
    """An item without an id marks words, and columns may have the names that the search uses."""
    text = "one two three four five six seven eight nine ten eleven"
    docs = frame([text, "clean words only"]).selectExpr("*", "1 as __hits", "'x' as __items", "2 as __n_words", "3 as text_")
    table = spark.createDataFrame([(None, text), ("b", text)], "item_id string, text string")
    found = {r["doc_id"]: r for r in d.op10(docs, table).collect()}
    assert found[0]["n_items"] == 1 and found[0]["n_hit"] == 11 and found[0]["items_sha256"] == hashlib.sha256(b"b").hexdigest()
    kept = d.decontaminate(docs, table)
    assert kept.columns == docs.columns and [r["doc_id"] for r in kept.collect()] == [1]
    assert [r["doc_id"] for r in d.decontaminate(docs, table.where("item_id is null")).collect()] == [1]


def test_very_long_text(spark, frame):
    """A text larger than a block of texts is one shard."""
    item = "one two three four five six seven eight nine ten"
    long = "filler words " * 250_000 + item + " end " + "b" * 300_000
    found = {r["doc_id"]: r for r in d.op10(frame([long, "x"]), spark.createDataFrame([(1, item)], "item_id long, text string")).collect()}
    assert found[0]["n_words"] == 500_012 and found[0]["n_hit"] == 10 and not found[1]["contaminated"]
