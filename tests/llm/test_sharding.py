import zlib
from collections import defaultdict

from tabletext.llm import sharding

from .conftest import corpus


def test_all_rows_in_order_with_near_equal_bytes(frame):
    texts = corpus(n=300)
    rows = sharding.op1(frame(texts)).collect()
    assert sorted(r["doc_id"] for r in rows) == list(range(len(texts)))
    shards = defaultdict(list)
    for r in rows:
        text = (texts[r["doc_id"]] or "").encode()
        assert r["size"] == len(text) + 1 and r["text_crc32"] == zlib.crc32(text) and r["law"] == "bytes" and r["grown_shard"] is None
        shards[r["shard"]].append(r)
    assert set(shards) == set(range(8))
    largest = max(r["size"] for r in rows)
    mean = sum(r["size"] for r in rows) / 8
    for own in shards.values():
        assert sorted(r["slot"] for r in own) == list(range(len(own)))
        assert abs(sum(r["size"] for r in own) - mean) <= largest + 0.01 * mean


def test_a_hot_group_is_split_only_as_far_as_balance_needs(frame):
    rows = sharding.op1(frame(["same text"] * 400 + [f"text {i}" for i in range(200)])).collect()
    sizes = defaultdict(int)
    for r in rows:
        sizes[r["shard"]] += r["size"]
    assert max(sizes.values()) - min(sizes.values()) <= 0.02 * sum(sizes.values()) / 8 + 20
    # equal texts are neighbours: all shards but two hold either only copies, or all or none of them
    mixed = [s for s in range(8) if 0 < sum(r["text_crc32"] == zlib.crc32(b"same text") for r in rows if r["shard"] == s) < sum(r["shard"] == s for r in rows)]
    assert len(mixed) <= 2


def test_small_and_empty(frame):
    assert sharding.op1(frame([])).count() == 0
    assert {(r["shard"], r["slot"]) for r in sharding.op1(frame([None])).collect()} <= {(s, 0) for s in range(8)}
    assert sharding.op1(frame([(1, "a"), (1, "a"), (None, None)])).count() == 3


def test_equal_rows_are_split_too(frame):
    rows = sharding.op1(frame([(7, "the very same row")] * 400)).collect()
    sizes = defaultdict(int)
    for r in rows:
        sizes[r["shard"]] += r["size"]
    assert len(rows) == 400 and len(sizes) == 8 and max(sizes.values()) - min(sizes.values()) <= 2 * 18
