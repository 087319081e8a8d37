"""Tag-path ratios against a plain version of the method, and that they decide where no name tells."""

import re
from html.parser import HTMLParser

import numpy as np
import pytest

from wordset.llm import html_extract as X

BOXES = {"html", "body", "div", "section", "center"}


class Plain(HTMLParser):
    """Blocks of a page of divs, headings, paragraphs and lists: text, nodes (path, length, marks), number of the container."""

    def __init__(self, source):
        super().__init__()
        self.open, self.count, self.out, self.skip = [], 0, [], False
        self.feed(source)
        self.close()

    def handle_starttag(self, tag, attrs):
        if tag in ("meta", "br"):
            if tag == "br" and self.out and self.out[-1][0]:
                self.out[-1][0].append(" ")
            return
        self.count += 1
        if tag in ("div", "p", "ul", "li", "h1", "h2"):
            if any(t == "p" for t, _ in self.open):
                at = max(i for i, (t, _) in enumerate(self.open) if t == "p")
                del self.open[at:]
            self.out.append(([], [], None))
        self.open.append((tag, self.count))

    def handle_endtag(self, tag):
        if any(t == tag for t, _ in self.open):
            at = max(i for i, (t, _) in enumerate(self.open) if t == tag)
            if any(t in ("div", "p", "ul", "li", "h1", "h2", "body", "html") for t, _ in self.open[at:]):
                self.out.append(([], [], None))
            del self.open[at:]

    def handle_data(self, data):
        names = [t for t, _ in self.open]
        if {"script", "style", "title", "head"} & set(names):
            return
        if not self.out:
            self.out.append(([], [], None))
        text, nodes, _ = self.out[-1]
        if not "".join(text).strip():
            box = next((k for t, k in reversed(self.open) if t in BOXES), 0)
            self.out[-1] = (text, nodes, box)
            text, nodes, _ = self.out[-1]
        text.append(data)
        if data.strip():
            nodes.append((">".join(names), len(data), len(re.findall(r"[.,;:!?…]", data))))

    def blocks(self):
        return [(" ".join("".join(t).split()), n, box) for t, n, box in self.out if "".join(t).strip()]


def plain_selected(source):
    blocks = Plain(source).blocks()
    paths = {}
    for _, nodes, _ in blocks:
        for p, n, k in nodes:
            paths.setdefault(p, []).append((n, k))

    def ratio(nodes, which):
        total = sum(n for _, n, _ in nodes)
        return sum(n / total * sum(x[which] for x in paths[p]) / len(paths[p]) for p, n, _ in nodes)

    values = [(ratio(n, 0), ratio(n, 1)) for _, n, _ in blocks]
    fused = []
    for i, (_, _, box) in enumerate(blocks):
        row = [j for j in range(len(blocks)) if blocks[j][2] == box]
        at = row.index(i)
        weight = {row[at + d]: w for d, w in ((-2, 1), (-1, 2), (0, 4), (1, 2), (2, 1)) if 0 <= at + d < len(row)}
        text, marks = (sum(w * values[j][c] for j, w in weight.items()) / sum(weight.values()) for c in (0, 1))
        fused.append(text * (1 + marks))
    mean = {}
    for p in paths:
        part = [(n, f) for (_, nodes, _), f in zip(blocks, fused, strict=True) for q, n, _ in nodes if q == p]
        mean[p] = sum(n * f for n, f in part) / sum(n for n, _ in part)
    score = [sum(n * mean[p] for p, n, _ in nodes) / sum(n for _, n, _ in nodes) for _, nodes, _ in blocks]
    centre = sum(score) / len(score)
    level = X.LEVEL * (sum((s - centre) ** 2 for s in score) / len(score)) ** 0.5
    return [t for t, _, _ in blocks], [s >= level * (1 - 1e-12) for s in score]


def neutral(source):
    """The page with divs for all telling elements and without classes."""
    return re.sub(r"<(/?)(nav|article|footer|header|main|aside)\b[^>]*>", r"<\1div>", source).replace('<div class="ad">', "<div>")


@pytest.fixture(scope="module")
def given(spark, sf):
    return [r.html for r in spark.read.parquet(f"{sf}/pages.parquet").select("html").collect()][:120]


def test_selection_agrees_with_the_plain_version(given):
    for source in map(neutral, given):
        page = X._Page(source)
        texts, want = plain_selected(source)
        assert [t for t, _, _ in page.blocks] == texts
        assert X.selected(page.blocks, page.names).tolist() == want


def test_what_is_selected_is_returned_and_the_ratios_decide(given, monkeypatch):
    found = {s: X.extract(s) for s in map(neutral, given)}
    for source, text in found.items():
        texts, want = plain_selected(source)
        out = text.split("\n\n")
        assert all(t in out for t, w in zip(texts, want, strict=True) if w)
    monkeypatch.setattr(X, "_ratios", lambda b: (np.ones(len(b)), np.ones(len(b))))
    assert sum(X.extract(s) != t for s, t in found.items()) > 0.9 * len(found)


def test_articles_without_any_telling_name(given):
    whole = exact = 0
    for source in given:
        want = X.extract(source)
        out = X.extract(neutral(source))
        whole += all(p in out.split("\n\n") for p in want.split("\n\n"))
        exact += out == want
    assert whole >= 0.95 * len(given) and exact >= 0.5 * len(given)


def test_menus_and_teasers_without_marks_go():
    long = "<p>" + "A sentence of the article, with marks; it goes on. " * 8 + "</p>"
    menu = "<div><ul>" + "<li><a href='/x'>Menu</a></li>" * 12 + "</ul></div>"
    page = f"<body>{menu}<div>Buy now</div><div><h2>Title</h2>{long}<ul><li>first</li><li>second</li></ul>{long}<table><tr><td>1<td>2</table></div><div>All rights kept</div></body>"
    out = X.extract(page).split("\n\n")
    assert out[0] == "Title" and out[2:4] == ["first", "second"] and out[-2:] == ["1", "2"] and len(out) == 7


def test_very_long_page_and_clashing_columns(spark):
    para = "<p>" + "words of a long page, and more of them. " * 20 + "</p>"
    rows = [(1, "u", f"<body><nav><a>x</a></nav><article><h1>T</h1>{para * 4000}</article></body>", "t", "n"), (1, "u", None, None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars string")
    got = X.main_text(df).collect()
    assert sorted(r.n_chars for r in got) == [0, 1 + 4000 * 801] and X.main_text(df).columns == ["page_id", "url", "text", "n_chars"]
