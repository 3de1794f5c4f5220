import uuid

import pytest
from tokenizers import Tokenizer

from tabletext.llm import token_counts, tokens

from .conftest import corpus

EXTRA = ["a <|endoftext|> b", "it's we'll I'd\r\n\r\n  x   ", "٣٤ ½ ² 日本語 ok", "a b c  d", "🙂🙂 end", "x" * 3000, "<|endoftext|>"]


def test_counts_are_those_of_the_library(spark, frame, tmp_path):
    texts = corpus() + EXTRA
    whole = Tokenizer.from_file(tokens.vocabulary_path())
    path = f"file://{tmp_path}/{uuid.uuid4().hex}"
    docs = frame(texts)
    rows = {r["doc_id"]: r for r in token_counts.token_counts(docs, path).collect()}
    for i, t in enumerate(texts):
        n = len(whole.encode(t or "", add_special_tokens=False).ids)
        assert (rows[i]["n_tokens"], rows[i]["n_bytes"], rows[i]["over_limit"]) == (n, len((t or "").encode()), n > 1024)
    stored = token_counts.read_cache(spark, path)
    assert stored.count() == len({t or "" for t in texts})
    # another run encodes nothing, a new text is one miss
    assert token_counts.missing_texts(docs, stored).count() == 0
    token_counts.token_counts(frame([*texts, "new one"]), path).collect()
    assert token_counts.read_cache(spark, path).count() == len({t or "" for t in texts}) + 1


def test_empty(frame, tmp_path):
    assert token_counts.token_counts(frame([]), f"file://{tmp_path}/c").count() == 0


@pytest.mark.parametrize("name", ["word_bpe_49k.json", "piece_bpe_32k.model"])
def test_other_vocabularies(frame, tmp_path, name):
    row = token_counts.token_counts(frame(["hello world"]), f"file://{tmp_path}/c", tokens.vocabulary_path(name)).first()
    assert 0 < row["n_tokens"] < 8
