import random

import pytest

from tabletext.shipping import ship

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session", autouse=True)
def shipped(spark):
    ship(spark)


@pytest.fixture(scope="session")
def frame(spark):
    """Documents from texts, or from (id, text) pairs."""

    def make(texts, lang="en"):
        rows = [(t if isinstance(t, tuple) else (i, t)) for i, t in enumerate(texts)]
        return spark.createDataFrame([(i, t, lang, "s", len(t or "")) for i, t in rows], SCHEMA)

    return make


def corpus(seed: int = 7, n: int = 60) -> list:
    """Random texts with copies, near copies, shared passages, empty, null and repetitive ones."""
    r = random.Random(seed)
    words = ["alpha", "Béta", "gam-ma", "d.", "x1", "İı", "zeta", "eta9", "THE", "of", "日本", "q"] + [f"w{i}" for i in range(150)]
    say = lambda k: " ".join(r.choice(words) for _ in range(k))
    shared = [say(60), say(25), say(140)]
    out = [None, "", " \t\n", "one", "to " * 300, "a" * 900, "Ab" * 700]
    for i in range(n):
        text = say(r.randint(1, 220))
        if i % 4 == 0:
            cut = r.randint(0, len(text))
            text = text[:cut] + " " + r.choice(shared) + r.choice(["", " ", "\n"]) + text[cut:]
        out.append(text)
        if i % 7 == 0:
            out += [text] * r.randint(1, 3)
        if i % 5 == 0:
            parts = text.split(" ")
            parts[r.randrange(len(parts))] = "changed"
            out.append(" ".join(parts))
    out += [out[-1] + " tail"] * 2
    return out
