"""Disguised toxic documents are found by restoring them, and not without."""

import random
import uuid

import pyarrow as pa
import pytest

from wordset.llm import toxicity
from wordset.llm.labelled import held_out

DATA = "/root/testdata/sf0.1"
SIGNS = {"a": "4@", "e": "3", "i": "1!", "o": "0", "s": "5$", "t": "7+", "b": "8", "l": "1|", "g": "9", "z": "2"}


class Held:
    def __init__(self, value):
        self.value = value


def disguise(word, r):
    kind = r.randrange(4)
    at = [i for i, c in enumerate(word) if c in SIGNS]
    if kind == 0 and at:
        for i in r.sample(at, min(2, len(at))):
            word = word[:i] + r.choice(SIGNS[word[i]]) + word[i + 1 :]
        return word
    if kind == 1:
        return r.choice((" ", ".", " - ", "-", "_")).join(word)
    i = r.randrange(1, len(word) - 1)
    if kind == 2:
        return word[:i] + word[i] * r.randint(2, 4) + word[i + 1 :]
    return word[:i] + r.choice(".*_-") * (1 if word[i] != "*" else 2) + word[i:]


@pytest.fixture(scope="module")
def model(spark):
    docs, labels = spark.read.parquet(f"{DATA}/documents.parquet"), spark.read.parquet(f"{DATA}/labels.parquet")
    costs = toxicity.trigram_costs(docs)
    fitted = toxicity.fit(docs, labels, toxicity._shared(spark, costs))
    toxic = [r.text for r in docs.join(labels.filter("toxic = 1"), "doc_id").filter(held_out(docs.doc_id)).select("text").collect()]
    clean = [r.text for r in docs.join(labels.filter("toxic = 0"), "doc_id").filter(held_out(docs.doc_id)).select("text").collect()]
    return costs, fitted, toxic, clean


def scores(texts, costs, fitted):
    toxicity._cache.clear()
    return toxicity.score_array(pa.array(texts), (uuid.uuid4().hex, Held(costs)), (uuid.uuid4().hex, Held(fitted))).to_pylist()


def disguised(texts, weights, r):
    def one(word):
        low = word.lower().strip(".,;:!?")
        return disguise(low, r) if len(low) > 3 and any(f in weights for f in toxicity.word_features(low)) else word

    return [" ".join(map(one, t.split())) for t in texts]


def test_restoring_finds_disguised_documents(model, monkeypatch):
    costs, fitted, toxic, clean = model
    plain = scores(toxic, costs, fitted)
    known = [t for t, s in zip(toxic, plain, strict=True) if s >= toxicity.THRESHOLD]
    assert len(known) > 100
    odd = disguised(known, fitted[1], random.Random(4))
    found = sum(s >= toxicity.THRESHOLD for s in scores(odd, costs, fitted))
    false = sum(s >= toxicity.THRESHOLD for s in scores(clean, costs, fitted))
    monkeypatch.setattr(toxicity.Channel, "restore", lambda self, word, spaced=False: word)
    without = sum(s >= toxicity.THRESHOLD for s in scores(odd, costs, fitted))
    print(f"disguised {len(known)}: found {found}, without restoring {without}; clean {len(clean)}: false {false}")
    assert found >= 0.8 * len(known) and without <= 0.5 * found
    assert false <= 0.01 * len(clean)


def test_long_texts_are_counted_as_one(monkeypatch):
    text = "letters of a long text, all alike " * 40
    count = lambda: next(toxicity.count_batches([pa.RecordBatch.from_arrays([pa.array([text, None, ""])], ["text"])]))
    whole = count()
    monkeypatch.setattr(toxicity, "_PIECE", 37)
    assert count().equals(whole)


@pytest.mark.parametrize("odd, meant", [("stuupid", "stupid"), ("idiiot", "idiot"), ("l00ser", "loser")])
def test_letters_written_twice(odd, meant):
    from tests.llm.test_operators import small_channel

    assert small_channel().words(odd) == [meant]


@pytest.mark.parametrize("odd", ["i  d  i  o  t", "i - d - i - o - t", "m _ o _ r _ o _ n"])
def test_separators_of_some_length(odd):
    from tests.llm.test_operators import small_channel

    assert {"idiot", "moron"} & set(small_channel().apart(f"such a {odd} here"))
