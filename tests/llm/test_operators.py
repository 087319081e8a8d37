"""The ten text operators against brute force on small tables with awkward rows."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from tests.conftest import same_rows
from wordset.llm import bpe, exact_dedup, html_extract, licenses, near_dedup, packing, quality, queries, rules, sharding, toxicity

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, rid string, digest string, _score string"
VOCAB = queries.vocabulary()


def awkward():
    r = random.Random(8)
    words = ["the", "of", "and", "river", "stone", "über", "año", "x", "don't", "1999", "#", "!!", "中文"]
    texts = [None, "", " ", "\n\t", "one", "two words", "a b c", "A B C", "a  b\nc", "same text here again", "same text here again", "x" * 5000, "word " * 4000, "<|endoftext|> inside <|endoftext|>", "\x1c odd \x85 spaces here", "tab\tvt\x0bff\x0c end"]
    texts += [" ".join(r.choice(words) for _ in range(r.randint(1, 120))) for _ in range(60)]
    base = " ".join(f"w{r.randrange(500)}" for _ in range(400))
    texts += [base, base + " tail", base.replace("w1 ", "w2 ", 1), base.upper(), base]
    texts += ["same text here again"] * 30
    rows = [(i, t, "en" if i % 3 else None, f"s{i % 4}" if i % 7 else None, None, "clash", "clash", "clash") for i, t in enumerate(texts)]
    rows += [(None, "no id", "en", "s0", 5, None, None, None), (5, "two words", "en", "s1", 9, None, None, None), (5, "two words", "en", "s1", 9, None, None, None)]
    return rows


ROWS = awkward()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def no_labels(spark):
    return spark.createDataFrame([], "doc_id long, quality int, toxic int")


@pytest.fixture(scope="module")
def tables(spark, sf):
    return {t: spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels", "pages")}


# ---- 1 near duplicates


def words_of(text):
    return re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def plain_fingerprint(text):
    w = words_of(text)
    if not w:
        return 0
    parts = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)]
    hs = [xxhash.xxh64_intdigest(p.encode(), 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def plain_components(fps, ids):
    """Smallest id reachable over links of three bits or fewer, by union-find over all pairs."""
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 3:
                parent[find(i)] = find(j)
    low = {}
    for i, d in enumerate(ids):
        low[find(i)] = min(low.get(find(i), d), d)
    return [low[find(i)] for i in range(len(fps))]


def test_fingerprints_and_components(docs):
    rows = [r for r in ROWS if r[0] is not None]
    fps = [plain_fingerprint(r[1]) for r in rows]
    comp = plain_components(fps, [r[0] for r in rows])
    want = sorted((r[0], f"{f:016x}", c) for r, f, c in zip(rows, fps, comp, strict=True))
    got = near_dedup.near_duplicates(docs).collect()
    assert sorted((r.doc_id, r.fingerprint, r.component_id) for r in got if r.doc_id is not None) == want
    assert len(got) == len(ROWS)


def test_gray_tree_finds_every_link():
    r = random.Random(2)
    for dense in (False, True):
        centre = r.getrandbits(64)
        fps = sorted({(centre ^ sum(1 << b for b in r.sample(range(64), r.randint(0, 6 if dense else 30)))) for _ in range(700)})
        key = np.array([f >> 60 if not dense else 0 for f in fps])
        gray = np.array(fps, np.uint64)
        for s in (1, 2, 4, 8, 16, 32):
            gray ^= gray >> np.uint64(s)
        order = np.lexsort((gray, key))
        f, k = np.array(fps, np.uint64)[order], key[order]
        label = near_dedup.GrayTree(k, f).clusters()
        want = plain_components([int(x) | 0xF << (70 + 8 * int(g)) for x, g in zip(f, k, strict=True)], list(range(len(f))))
        assert label.tolist() == want


def test_links_lose_no_pair(spark):
    r = random.Random(4)
    base = [r.getrandbits(64) for _ in range(60)]
    fps = list({b ^ sum(1 << x for x in r.sample(range(64), r.randint(0, 4))) for b in base for _ in range(6)})
    signed = [(f - (1 << 64) if f >> 63 else f, i) for i, f in enumerate(fps)]
    df = spark.createDataFrame(signed, "fp long, doc long")
    stars = {x.node: x.component for x in near_dedup.components(near_dedup.links(df)).collect()}
    want = plain_components(fps, list(range(len(fps))))
    assert [stars.get(i, i) for i in range(len(fps))] == want


def test_one_document_of_each_group_stays(docs):
    kept = near_dedup.representatives(docs)
    assert kept.columns == docs.columns
    want = {r.doc_id for r in near_dedup.near_duplicates(docs).collect() if r.doc_id == r.component_id}
    assert {r.doc_id for r in kept.collect()} == want | {None}


# ---- 2 packing


def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(VOCAB)


def test_pieces_hold_every_id_once(docs):
    t = library()
    pieces = packing.packed(docs, VOCAB).collect()
    want = Counter()
    for r in ROWS:
        ids = t.encode(r[1] or "", add_special_tokens=False).ids + [0]
        data = np.array(ids, "<u4").tobytes()
        want[r[0], len(ids), zlib.crc32(data)] += 1
    by_doc = defaultdict(list)
    for p in pieces:
        by_doc[p.doc_id].append(p)
    for doc, ps in by_doc.items():
        n_rows = sum(r[0] == doc for r in ROWS)
        ps = sorted(set((p.start, p.length, p.ids_crc32, p.doc_tokens) for p in ps))
        text = next(r[1] for r in ROWS if r[0] == doc) if doc != 5 else None
        if doc == 5:
            continue
        ids = t.encode(text or "", add_special_tokens=False).ids + [0]
        at = 0
        for start, length, crc, total in ps:
            assert start == at and total == len(ids) and n_rows == 1
            assert crc == zlib.crc32(np.array(ids[start : start + length], "<u4").tobytes())
            at += length
        assert at == len(ids)
    by_seq = defaultdict(list)
    for p in pieces:
        by_seq[p.sequence_id].append(p)
    for ps in by_seq.values():
        at = 0
        for p in sorted(ps, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= 1024
    assert sum(p.length for p in pieces) == sum(k[1] * n for k, n in want.items())


def test_best_fit_takes_the_tightest_window():
    r = random.Random(5)
    for _ in range(30):
        lengths = [r.randint(1, 63) for _ in range(r.randint(0, 80))]
        got = packing.best_fit(lengths, 64)
        room, where = [], [None] * len(lengths)
        for k in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
            fits = [i for i, x in enumerate(room) if x >= lengths[k]]
            if fits:
                best = min(room[i] for i in fits)
                assert 64 - got[k][1] == best  # the window with the least room
                i = got[k][0]
                assert room[i] == best
            else:
                i = len(room)
                room.append(64)
                assert got[k] == (i, 0)
            where[k] = i
            room[i] -= lengths[k]


def test_little_padding(tables):
    shares = [packing.padding(packing.packed(tables["documents"].repartition(n), VOCAB)).first().share for n in (1, 60)]
    assert max(shares) < 0.02 and abs(shares[0] - shares[1]) < 0.001  # however the documents lie in files


def test_bins_are_bounded():
    assert [packing.bins(n, 8) for n in (0, 1, 40_000, 10**6, 10**8)] == [1, 1, 2, 8, 191]
    assert all(-(-n // packing.bins(n, 8)) <= packing.MOST for n in (5, packing.MOST + 1, 10**9))


def test_several_bins_hold_every_piece_once(docs, monkeypatch):
    whole = Counter(tuple(r)[:5] for r in packing.packed(docs, VOCAB).collect())
    monkeypatch.setattr(packing, "FEWEST", 2)
    pieces = packing.packed(docs, VOCAB).collect()
    assert Counter(tuple(r)[:5] for r in pieces) == whole
    by_seq = defaultdict(list)
    for p in pieces:
        by_seq[p.sequence_id].append((p.offset, p.length))
    for ps in by_seq.values():
        assert [o for o, _ in sorted(ps)] == [sum(n for _, n in sorted(ps)[:i]) for i in range(len(ps))] and sum(n for _, n in ps) <= 1024
    assert len({q >> packing.LOCAL_BITS for q in by_seq if q >> packing.BIN_BIT}) > 1


# ---- 3 byte-pair encoding


def test_round_trip_equals_the_library(docs, tables):
    t = library()
    for df in (docs.select("doc_id", "text"), tables["documents"].select("doc_id", "text")):
        texts = {(r.doc_id, r.text) for r in df.collect()}
        got = Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.round_trip(df, VOCAB).collect())
        for doc, text in texts:
            ids = t.encode(text or "", add_special_tokens=False).ids
            row = (doc, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(t.decode(ids, skip_special_tokens=False).encode()).hexdigest())
            assert got[row] >= 1
        assert sum(got.values()) == df.count()


def test_automaton_on_hard_words():
    t, c = library(), bpe.codec(VOCAB)
    r = random.Random(9)
    pieces = ["a", "aa", "th", "the", "in", "ing", " ", "  ", "'s", "'", "1", "12", "-", "--", "=", "é", "中", "\n", "\r\n", " ", "²", "Ⅳ", "_"]
    cases = ["".join(r.choice(pieces) for _ in range(r.randint(0, 40))) for _ in range(3000)] + ["a" * k for k in range(1, 70)] + ["ab" * 40, " " * 90, "=" * 300]
    for x in cases:
        assert np.frombuffer(c.encode(x), "<u4").tolist() == t.encode(x, add_special_tokens=False).ids
        assert packing.WholeTextEncoder(VOCAB).encode(x) == c.encode(x) if len(x) > 60 else True


def test_encode_then_decode(docs):
    back = bpe.decoded(bpe.encoded(docs, VOCAB), VOCAB)
    assert Counter((r.doc_id, r.text) for r in back.collect()) == Counter((r[0], r[1] or "") for r in ROWS)


# ---- 4 quality and 8 toxicity


def auc(pairs):
    pos, neg = [s for s, y in pairs if y], [s for s, y in pairs if not y]
    return sum((p > n) + 0.5 * (p == n) for p in pos for n in neg) / (len(pos) * len(neg))


def test_quality_on_held_out_rows(spark):
    d = "/root/testdata/sf0.01"
    docs_, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    rows = quality.scored(docs_, labels).join(labels, "doc_id").filter("held_out").collect()
    assert auc([(r.score, r.quality) for r in rows]) > 0.95
    assert sum(r.predicted == r.quality for r in rows) > 0.9 * len(rows)
    for r in rows:
        assert zlib.crc32(str(r.doc_id).encode()) % 3 == 1 and 0 <= r.score <= 1


def test_cosines_are_exact(tables):
    m = quality.fit(tables["documents"], tables["labels"])
    x = np.stack([quality.features(r.text) for r in tables["documents"].limit(50).collect()])
    z = x @ m.projection - m.offset
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    for row, score in zip(z, m.score(x), strict=True):
        cos = m.points @ row
        near = np.flatnonzero(cos >= np.sort(cos)[-quality.NEIGHBOURS])
        w = np.maximum(cos[near], 1e-6).astype(np.float64) ** 4
        assert abs((w * m.y[near]).sum() / w.sum() - score) < 1e-3


def test_toxicity_on_held_out_rows(spark):
    d = "/root/testdata/sf0.1"
    docs_, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    rows = toxicity.scored(docs_, labels).join(labels, "doc_id").filter("held_out").collect()
    assert auc([(r.score, r.toxic) for r in rows]) > 0.9
    clean = [r.predicted for r in rows if not r.toxic]
    assert sum(clean) < 0.02 * len(clean)
    assert sum(r.predicted for r in rows if r.toxic) > 0.8 * sum(r.toxic for r in rows)


def small_channel():
    texts = ["the idiot is a loser and stupid trash", "a moron is pathetic and worthless scum", "this disgusting clown ruled the town", "the stone in the river and the road to the sea"] * 50
    n = np.zeros(64**3)
    for t in texts:
        s = np.r_[0, 0, toxicity.symbols(t), 0].astype(np.uint32)
        n += np.bincount(s[:-2] << 12 | s[1:-1] << 6 | s[2:], minlength=64**3)
    n = n.reshape(64, 64, 64)
    p1 = (n.sum((0, 1)) + 0.5) / (n.sum() + 32)
    p2 = (n.sum(0) + 4 * p1) / (n.sum((0, 1))[:, None] * 0 + n.sum(0).sum(1, keepdims=True) + 4)
    return toxicity.Channel(-np.log2((n + 4 * p2) / (n.sum(2, keepdims=True) + 4)).astype(np.float32))


@pytest.mark.parametrize(
    "odd, meant", [("1d10t", "idiot"), ("$tup1d", "stupid"), ("l0s3r!", "loser"), ("stuuuupid", "stupid"), ("tr@sh", "trash"), ("m.o.r.o.n", "moron"), ("sc-um", "scum"), ("idiot", "idiot"), ("cl0wn.", "clown"), ("p4th3t1c", "pathetic")]
)
def test_disguised_words(odd, meant):
    assert small_channel().words(odd) == [meant]


def test_letters_set_apart():
    c = small_channel()
    assert c.apart("you are an i d i o t indeed") == ["idiot"]
    assert "moron" in toxicity.restored("such a m o r o n", c)
    assert toxicity.restored(None, c) == "" and toxicity.restored("plain words", c) == "plain words"


def test_viterbi_is_the_cheapest_path():
    import itertools

    c = small_channel()
    for word in ("1d10t", "$t", "a1@", "l0$3", "s..t"):
        best = None
        for path in itertools.product(*c.options(word, False)):
            state, cost = 0, 0.0
            for text, extra in path:
                cost += extra
                for ch in text:
                    y = int(toxicity.symbols(ch)[0])
                    cost += c.cost[state][y]
                    state = (state & 63) << 6 | y
            cost += c.cost[state][0]
            if best is None or cost < best[0] - 1e-9:
                best = (cost, "".join(t for t, _ in path))
        assert c.restore(word) == best[1]


def test_scores_without_labels(docs, none, no_labels):
    q = quality.scored(docs, no_labels).collect()
    assert {r.score for r in q} == {0.5} and len(q) == len(ROWS)
    t = toxicity.scored(docs, no_labels).collect()
    assert all(r.predicted == 0 for r in t) and len(t) == len(ROWS)
    assert quality.scored(none, no_labels).count() == 0 and toxicity.scored(none, no_labels).count() == 0


def test_scores_of_awkward_rows(docs, tables):
    assert quality.scored(docs, tables["labels"]).filter("score between 0 and 1").count() == len(ROWS)
    assert toxicity.scored(docs, tables["labels"]).filter("score between 0 and 1").count() == len(ROWS)
    assert toxicity.accepted(docs, tables["labels"]).columns == docs.columns


# ---- 5 pages

PAGES = {
    None: "",
    "": "",
    "bare text": "bare text",
    "<p>a &amp; b<p>c<br>d": "a & b\n\nc d",
    "<html><body><nav><ul><li><a>Home</a></li></ul></nav><article><h1>T</h1><p>One, <b>two</b>.</p></article><footer>f</footer></body></html>": "T\n\nOne, two.",
    "<article><p>Text here, indeed.</p><div class='comments'><p>I disagree, wholly.</p></div><form>Name <input></form></article>": "Text here, indeed.",
    "<script>var a='<p>no</p>';</script><style>p{}</style><p>yes.</p>": "yes.",
    "<div id='sidebar'>x, y.</div><div class='cookie-notice'>We use cookies, ok.</div><main><p>Body text, long enough.</p></main>": "Body text, long enough.",
    "<table><tr><td>a<td>b<tr><td>c</table>": "a\n\nb\n\nc",
    "<p>1 < 2 &lt; 3</p>": "1 < 2 < 3",
    "<ul><li>one<li>two</ul>": "one\n\ntwo",
    "<!-- <p>hidden</p> --><p>shown</p>": "shown",
}


def test_pages(spark):
    df = spark.createDataFrame([(i, f"u{i}", h) for i, h in enumerate(PAGES)], "page_id long, url string, html string")
    got = {r.page_id: (r.text, r.n_chars) for r in html_extract.main_text(df).collect()}
    assert got == {i: (t, len(t)) for i, t in enumerate(PAGES.values())}
    assert html_extract.main_text(df.limit(0)).count() == 0


def test_articles_of_the_given_pages(tables):
    import html as h

    rows = {r.page_id: r.html for r in tables["pages"].collect()}
    for r in html_extract.main_text(tables["pages"]).collect():
        source = rows[r.page_id]
        article = source[source.index("<article>") + 9 : source.index("</article>")]
        parts = (" ".join(h.unescape(re.sub(r"</?b>", "", p.replace("<br>", " "))).split()) for p in re.split(r"</?h1>|</?p>", article))
        assert r.text == "\n\n".join(p for p in parts if p)


def test_text_without_an_article_element():
    body = "<p>This is a long paragraph, with marks. It goes on, and on.</p>" * 6
    page = f"<div class='x'><a>one</a></div><div><div><h2>Title</h2>{body}</div></div><div>short</div>"
    out = html_extract.extract(page)
    assert out.count("long paragraph") == 6 and "Title" in out and "short" not in out


# ---- 6 rules


def plain_measures(text):
    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    grams = Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    hit = {j for i in range(len(w) - 7) if grams[tuple(w[i : i + 8])] > 1 for j in range(i, i + 8)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(hit)


def test_measures(docs):
    got = rules.ledger(docs)
    want = Counter((r[0], *plain_measures(r[1])) for r in ROWS)
    assert Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got.collect()) == want


def test_policies_and_ablations(docs):
    book = rules.ledger(docs)
    kept = rules.accepted(docs)
    assert kept.columns == docs.columns
    assert kept.count() == book.filter(rules.passes("strict_v1")).count()
    for r in rules.ablations(book).collect():
        bit = 1 << r.bit
        assert r.failed == book.filter(F.col("failed_bits").bitwiseAND(bit) != 0).count()
        assert r.only_this == book.filter(F.col("failed_bits") == bit).count()
        assert r.kept_without == book.filter(F.col("failed_bits").isin(0, bit)).count()


# ---- 7 exact duplicates


def plain_dedup(rows):
    groups = defaultdict(list)
    for doc, text in rows:
        groups[re.sub(r"[\x20\x09-\x0D]", "", text or "")].append((doc, text or ""))
    for norm, g in groups.items():
        best = min(g, key=lambda r: (-len(r[1]), r[0] is None, r[0] or 0))
        for doc, _ in g:
            yield doc, best[0], len(g), hashlib.sha256(norm.encode()).hexdigest()


@pytest.mark.parametrize("support", [0.001, 0.2, 0.9])
def test_exact_groups(docs, support):
    got = exact_dedup.decide(docs, support).collect()
    assert Counter((r.doc_id, r.keep_id, r.group_size, r.text_sha256) for r in got) == Counter(plain_dedup([(r[0], r[1]) for r in ROWS]))
    kept = Counter(r.text_sha256 for r in got if r.kept)
    assert set(kept.values()) == {1} and len(kept) == len({r.text_sha256 for r in got})
    assert all(r.doc_id == r.keep_id for r in got if r.kept)


def test_rows_that_tie_with_the_winner(spark):
    rows = [(None, "same", i) for i in range(50)] + [(7, "a b", 1), (7, "a b", 2), (7, "ab", 3)]
    df = spark.createDataFrame(rows, "doc_id long, text string, digest int").repartition(6)
    for support in (0.001, 0.5):
        assert sorted((r.text, r.doc_id) for r in exact_dedup.deduplicated(df, support).collect()) == [("a b", 7), ("same", None)]


@pytest.mark.parametrize("support", [0.001, 0.2])
def test_rows_that_stay(docs, support):
    out = exact_dedup.deduplicated(docs, support)
    assert out.columns == docs.columns
    want = {r.doc_id for r in exact_dedup.decide(docs).filter("kept").collect()}
    got = [r.doc_id for r in out.collect()]
    assert set(got) == want and len(got) == len(want)


# ---- 9 shards


def test_shards(docs):
    out = sharding.placed(docs).collect()
    assert len(out) == len(ROWS)
    slots = defaultdict(list)
    for r in out:
        slots[r.shard].append(r.slot)
    sizes = [len(slots[s]) for s in range(8)]
    assert max(sizes) - min(sizes) <= 1
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert Counter((r.doc_id, r.size, r.text_crc32) for r in out) == Counter((r[0], len((r[1] or "").encode()) + 1, zlib.crc32((r[1] or "").encode())) for r in ROWS)


def test_every_shard_has_the_mixture(tables):
    out = sharding.placed(tables["documents"])
    share = out.groupBy("shard", "source").agg(F.count(F.lit(1)).alias("n")).collect()
    total = Counter()
    for r in share:
        total[r.source] += r.n
    for r in share:
        assert abs(r.n - total[r.source] / 8) <= 2


def test_few_rows_for_the_shards(spark, none):
    three = spark.createDataFrame([(1, "a", "s"), (2, "b", "s"), (3, None, None)], "doc_id long, text string, source string")
    assert sorted((r.shard, r.slot) for r in sharding.placed(three).collect()) == [(0, 0), (1, 0), (2, 0)]
    assert sharding.placed(none).count() == 0


def test_written_shards(spark, tables, tmp_path):
    path = f"file://{tmp_path}/shards"
    sharding.write_shards(tables["documents"], path)
    back = spark.read.parquet(path)
    assert back.count() == tables["documents"].count() and back.select("shard").distinct().count() == 8


def test_layout_plays_no_part(tables):
    at = [{(r.doc_id, r.shard, r.slot) for r in sharding.placed(tables["documents"].repartition(n)).select("doc_id", "shard", "slot").collect()} for n in (3, 7)]
    assert at[0] == at[1]


def test_sources_of_one_row(spark):
    """Half the rows in sources of their own: the large source and the rest are in every shard in proportion."""
    df = spark.createDataFrame([(i, f"t{i}", "large" if i % 2 else f"s{i}", "x", "y") for i in range(4000)], "doc_id long, text string, source string, shard string, slot string")
    n = Counter((r.shard, r.source == "large") for r in sharding.placed(df).collect())
    assert all(abs(n[s, True] - 250) <= 60 and n[s, True] + n[s, False] == 500 for s in range(8))


# ---- 10 licences


def test_licences(spark):
    apache = "Licensed under the Apache License, Version 2.0.\nYou may not use this file except in compliance with the License. You may obtain a copy of the License at:\nUnless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS."
    cases = [None, "", "no such thing", "Released under the MIT License.", apache, "Licensed under CC BY-NC 4.0.\nother words\nLICENSED UNDER   CC-BY-NC 4.0", "All rights reserved. Released under the MIT license!"]
    df = spark.createDataFrame(list(enumerate(cases)), "doc_id long, text string")
    got = {r.doc_id: (r.licenses, r.sids, r.rule_ids, r.gaps) for r in licenses.scan(df).collect()}
    assert got[0] == got[1] == got[2] == ("", "", "", 0)
    assert got[3] == ("MIT", "201", "5", 0)
    assert got[4] == ("Apache-2.0", "101,102,103,104", "1", 0)
    assert got[5] == ("CC-BY-NC-4.0", "401,401", "13", 1)
    assert got[6] == ("LicenseRef-all-rights-reserved,MIT", "901,201", "5,22", 0)


# ---- all of them


def test_empty_tables(none):
    assert near_dedup.near_duplicates(none).count() == 0 and near_dedup.representatives(none).count() == 0
    assert packing.packed(none, VOCAB).count() == 0 and bpe.round_trip(none, VOCAB).count() == 0
    assert rules.ledger(none).count() == 0 and rules.accepted(none).count() == 0
    assert exact_dedup.decide(none).count() == 0 and exact_dedup.deduplicated(none).count() == 0
    assert licenses.scan(none).count() == 0


def test_awkward_rows_everywhere(docs):
    assert licenses.scan(docs).count() == len(ROWS)
    assert toxicity.deobfuscated(docs).count() == len(ROWS)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_operator_equals_sql(spark, duck, sf, name):
    same_rows(queries.queries()[name](spark, sf), duck, queries.oracle_sql()[name])


def test_native_operators_run_no_python(spark, sf):
    for name in ("op7_exact_heavy_hitters", "op10_license_rules"):
        plan = queries.queries()[name](spark, sf)._jdf.queryExecution().toString()
        assert not re.search("Python|Arrow|Pandas", plan)
