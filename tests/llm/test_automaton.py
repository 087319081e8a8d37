"""The compiled tokenization automaton against the merges themselves, applied in order."""

import json
import random

from wordset.llm import bpe, queries


def small_vocabulary(tmp_path, seed, n=40):
    """A byte vocabulary with merges of its own tokens over three letters, the later the longer."""
    r = random.Random(seed)
    letters = list(bpe._byte_letters())
    vocab = {c: i for i, c in enumerate(letters)}
    made, merges = ["a", "b", "c"], []
    while len(merges) < n:
        u, v = r.choice(made), r.choice(made)
        if u + v not in vocab and len(u + v) < 12:
            vocab[u + v] = len(vocab)
            made.append(u + v)
            merges.append([u, v])
    path = tmp_path / f"v{seed}.json"
    path.write_text(json.dumps({"added_tokens": [], "pre_tokenizer": {"type": "ByteLevel"}, "model": {"vocab": vocab, "merges": merges}}))
    return str(path), vocab, merges


def plain_merges(word, merges):
    """Merges in order of their rank, each at all places from the left."""
    out = list(word)
    for u, v in merges:
        i = 0
        while i < len(out) - 1:
            if out[i] == u and out[i + 1] == v:
                out[i : i + 2] = [u + v]
            i += 1
    return out


def test_words_over_small_vocabularies(tmp_path):
    r = random.Random(3)
    for seed in range(12):
        path, vocab, merges = small_vocabulary(tmp_path, seed)
        a = bpe.Automaton(path)
        for _ in range(300):
            word = "".join(r.choice("abc") for _ in range(r.randint(1, 30)))
            want = [vocab[t] for t in plain_merges(word, merges)]
            assert a.encode_word(word.encode()) == want
            assert all(a.may_follow(x, y) for x, y in zip(want, want[1:], strict=False))


def test_arcs_are_those_of_words(tmp_path):
    """An arc x y is open exactly if the merges leave the two tokens apart."""
    for seed in range(6):
        path, vocab, merges = small_vocabulary(tmp_path, seed, 25)
        a = bpe.Automaton(path)
        name = {i: t for t, i in vocab.items()}
        live = [i for i in a.token.values() if set(name[i]) <= set("abc")]
        for x in live:
            for y in live:
                assert a.may_follow(x, y) == (plain_merges(name[x] + name[y], merges) == [name[x], name[y]])


def test_size_of_the_table_of_the_public_vocabulary():
    a = bpe.automaton(queries.vocabulary())
    t = a.table()
    assert t["states"] == len(a.born) and t["open_arcs"] + t["closed_arcs"] == t["states"] * a.width
    assert t["bytes"] < 20_000_000 and t["open_arcs"] > 2_000_000_000
    r = random.Random(1)
    tokens = list(a.token.values())
    for _ in range(20_000):
        x, y = r.choice(tokens), r.choice(tokens)
        assert a.may_follow(x, y) == a._open(x, y, 1 << 60)
