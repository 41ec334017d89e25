import random

import pytest

SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, shard string, slot string, node string, n_tokens string, score string, id string, spans_0 string"


def sentence(rng, n, words=("the", "of", "alpha", "beta", "gamma", "delta", "ring", "stone", "river", "glass", "Été", "über", "niño", "x9", "it's", "we're")):
    return " ".join(rng.choice(words) + (str(rng.randint(0, 400)) if rng.random() < 0.6 else "") for _ in range(n))


def odd_texts():
    """Nulls, empty and blank texts, copies, near copies, shared passages, very long and odd ones."""
    rng = random.Random(4)
    base, passage = [sentence(rng, 120) for _ in range(6)], sentence(rng, 70)
    near = []
    for b in base[:3]:
        w = b.split()
        for k in range(4):
            v = list(w)
            v[10 + 7 * k] = "changed"
            near.append(" ".join(v))
    shared = [sentence(rng, 40) + " " + passage + " " + sentence(rng, 30 + k) for k in range(5)]
    long = [sentence(rng, 9000), "a" * 60_000, " " * 30_000 + "b", "naïve 日本語 текст " * 3000]
    few = [None, None, "", "   \n\t", "one", "one", "two words", "four words are here", "now exactly five words here", "ONE", "12345 !!! ???", "<|endoftext|> x <|endoftext|>", "it's we're they'll'''re", " line sep\x85", "é combining"]
    return [*base, *base[:2], *near, *shared, *long, *few]


@pytest.fixture(scope="session")
def odd(spark):
    rows = [(k * 3, t, "en" if k % 2 else "de", "s", None if t is None else len(t), "c", "c", "c", "c", "c", "c", "c") for k, t in enumerate(odd_texts())]
    rows += [rows[0], rows[0], (None, "row without an id " * 30, None, None, None, *"ccccccc"), (None, None, None, None, None, *"ccccccc")]
    return spark.createDataFrame(rows, SCHEMA).repartition(5)


@pytest.fixture(scope="session")
def no_docs(odd):
    return odd.where("false")
