"""Pages whose article is easily cut: one long paragraph, parts beside it, words of classes and ids."""

import pytest

from wordset.llm.html_extract import extract

LONG = "It is a long paragraph, with marks; it goes on, and on. " * 30
LONG = LONG.strip()
LEAD = "A lead of some length, which says what follows."
WHOLE = {
    f"<div><p>Short one.</p><p>{LONG}</p><p>Short two.</p></div>": ["Short one.", LONG, "Short two."],
    f"<body><div><ul><li>One.<li>{LONG}<li>Two.</ul></div></body>": ["One.", LONG, "Two."],
    f"<body><div><p><span>{LONG}</span></p><p>End.</p></div></body>": [LONG, "End."],
    f"<body><div><h1>Title</h1><p>{LEAD}</p></div><div><p>{LONG}</p></div><div>more</div></body>": ["Title", LEAD, LONG],
    f"<body><div><h1>Title</h1></div><div><p>{LONG}</p></div><div>more</div></body>": ["Title", LONG],
    f"<body><article><p>{LONG}</p></article><article><h2>B</h2><p>{LEAD}</p></article><div>more</div></body>": [LONG, "B", LEAD],
    f"<body><div>{LEAD}</div><main><p>{LONG}</p><p>End.</p></main></body>": [LONG, "End."],
}


@pytest.mark.parametrize("page", WHOLE)
def test_one_paragraph_with_nearly_all_text(page):
    assert extract(page).split("\n\n") == WHOLE[page]


PARAGRAPH = "<p>This is a long paragraph, with marks. It goes on, and on, for quite a while.</p>"
BODY = PARAGRAPH * 6
WRAPPED = [
    f"<body><div class='{words}'><h1>Title</h1>{BODY}</div></body>" for words in ("has-sidebar", "content-with-sidebar", "page header-fixed", "no-comments", "sidebar", "search")
] + [
    f"<body><div class='modal'><article><h1>Title</h1>{BODY}</article></div><div class='comments'>{BODY}</div></body>",
    f"<body><div class='sidebar-left'>{PARAGRAPH[:20]}</div><article><h1>Title</h1>{BODY}</article><div class='ad-slot'>{BODY}</div></body>",
    f"<body><article><h1>Title</h1>{PARAGRAPH * 2}<section id='related-work'>{PARAGRAPH}</section><section id='discussion'>{PARAGRAPH}</section><div class='notice'>{PARAGRAPH * 2}</div></article></body>",
]


@pytest.mark.parametrize("page", WRAPPED)
def test_words_of_classes(page):
    out = extract(page)
    assert out.split("\n\n")[0] == "Title" and out.count("long paragraph") == 6


def test_words_that_mark_stay_out():
    for words in ("comments", "cookie-notice", "post-footer", "site_header", "shareButtons", "ad", "sidebar-1", "related-posts related"):
        assert extract(f"<body><article><h1>T</h1>{BODY}</article><div class='{words}'><a>short</a></div></body>").count("short") == 0
    assert "long" not in extract(f"<body><main><p>Main text, here.</p><div id='comments'>{BODY}</div></main></body>")


def test_headings_formulas_and_drawings():
    page = "<article><h2 id='search-algorithms'>Search</h2><p>Let <math><mi>x</mi><mo>=</mo><mfrac><mn>1</mn><mn>2</mn></mfrac></math> be.</p><svg><path d='M0'/><text>Label</text><text>two</text></svg><p>End.</p></article>"
    assert extract(page) == "Search\n\nLet x = 1 2 be.\n\nLabel two\n\nEnd."
