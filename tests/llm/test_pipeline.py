"""The pipeline's stages, each against brute force on what its predecessor kept."""

import re
import zlib

import numpy as np
import pytest

import corpus_pipeline
from tests.llm.test_operators import library, plain_components, plain_fingerprint
from wordset.functions.store import written
from wordset.llm import rules


@pytest.fixture(scope="module")
def kept(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    out = {"documents": docs}
    for name, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, sf), name)
        out[name] = docs
    return out


def ids(df):
    return {r.doc_id for r in df.select("doc_id").collect()}


def test_stages_return_the_columns_of_documents(kept):
    for name, _ in corpus_pipeline.STAGES[:-1]:
        assert kept[name].schema == kept["documents"].schema


def test_toxic_documents_go_and_clean_ones_stay(spark, sf, kept):
    labels = {r.doc_id: r.toxic for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    stay = ids(kept["toxicity"])
    clean = [d for d, t in labels.items() if not t]
    assert sum(d in stay for d in clean) >= 0.98 * len(clean)


def test_toxic_documents_go(spark):
    """On a table with enough of them to learn from."""
    d = "/root/testdata/sf0.1"
    stay = ids(corpus_pipeline.STAGES[0][1](spark, spark.read.parquet(f"{d}/documents.parquet"), d))
    rows = spark.read.parquet(f"{d}/labels.parquet").collect()
    toxic, clean = ([r.doc_id for r in rows if r.toxic == y] for y in (1, 0))
    assert len(toxic) > 300 and sum(x in stay for x in toxic) <= 0.12 * len(toxic)
    assert sum(x in stay for x in clean) >= 0.99 * len(clean)


def test_rules(kept):
    want = {r.doc_id for r in kept["toxicity"].collect() if not any(eval(c, {}, dict(zip(rules.MEASURES, rules.measure(r.text), strict=True))) for _, c in rules.RULES.values())}
    assert ids(kept["quality_rules"]) == want


def test_copies(kept):
    best = {}
    for r in kept["quality_rules"].collect():
        key = re.sub(r"[\x20\x09-\x0D]", "", r.text or "")
        best[key] = min(best.get(key, (1, 0)), (-len(r.text or ""), r.doc_id))
    assert ids(kept["exact_dedup"]) == {d for _, d in best.values()}


def test_near_copies(kept):
    rows = kept["exact_dedup"].collect()
    comp = plain_components([plain_fingerprint(r.text) for r in rows], [r.doc_id for r in rows])
    assert ids(kept["near_dedup"]) == {r.doc_id for r, c in zip(rows, comp, strict=True) if r.doc_id == c}


def test_packing(kept):
    t = library()
    pieces = kept["packing"].collect()
    total = 0
    texts = {r.doc_id: r.text for r in kept["near_dedup"].collect()}
    seen = {d: 0 for d in texts}
    for p in pieces:
        tokens = t.encode(texts[p.doc_id], add_special_tokens=False).ids + [0]
        assert p.ids_crc32 == zlib.crc32(np.array(tokens[p.start : p.start + p.length], "<u4").tobytes())
        seen[p.doc_id] += p.length
        total += p.length
    assert all(seen[d] == len(t.encode(x, add_special_tokens=False).ids) + 1 for d, x in texts.items())


def test_run_equals_the_stages(spark, sf, kept):
    key = lambda r: (r.doc_id, r.start, r.length, r.ids_crc32)
    assert sorted(map(key, corpus_pipeline.run(spark, sf).collect())) == sorted(map(key, kept["packing"].collect()))


def test_stages_on_awkward_rows(spark, sf):
    """Nulls, ties, repeated rows and clashing names pass all stages; what stays has its own contents."""
    from tests.llm.test_operators import ROWS

    names = "_score _m _n _dig _digest _at _gone gone row m digest n score restored_text shard slot".split()
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{n} string" for n in names)
    rows = [(*r[:5], *(f"{n}{r[0]}" for n in names)) for r in ROWS]
    docs = spark.createDataFrame(rows, schema)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {tuple(r) for r in docs.collect()}
        docs = written(stage(spark, docs, sf), name)
        assert docs.columns == [f.split()[0] for f in schema.split(", ")]
        after = [tuple(r) for r in docs.collect()]
        assert set(after) <= before and (len(after) < len(before) or name == "toxicity")
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert {r.doc_id for r in pieces.select("doc_id").collect()} == {r[0] for r in after}


def test_stages_on_an_empty_table(spark, sf):
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES:
        docs = written(stage(spark, docs, sf), name)
        assert docs.count() == 0
