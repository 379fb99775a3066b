"""Names of boilerplate on wrappers and modifiers."""

import pytest

from kernmill.llm.html_text import boilerplate, main_text
from tests.llm.test_page_regions import P, paras, whole


@pytest.mark.parametrize("name", ["with-sidebar", "no-sidebar", "has-comments", "post-share-enabled", "main-header-fixed", "page--with-nav", "entry-header"])
def test_modifiers_are_no_boilerplate(name):
    assert not boilerplate(name)
    assert whole(main_text(f"<body><div class='{name}'>{paras(P)}</div></body>"))
    assert whole(main_text(f"<body><div id='{name}'>{paras(P)}</div></body>"))


@pytest.mark.parametrize("name", ["ad", "sidebar", "site-header", "cookie-notice", "related-posts", "share-buttons", "wide sidebar_left", "ad-slot-2", "comments-area"])
def test_boilerplate_still_goes(name):
    assert boilerplate(name)
    assert main_text(f"<body><div class='{name}'>Some words of this kind that are no part of the story at all.</div><div>{paras(P)}</div></body>") == "\n".join(t.strip() for t in P)
    inline = main_text(f"<body><div><p>{P[0]}<span class='{name}'>Out</span> more words.</p>{paras(P[1:])}</div></body>")
    assert "Out" not in inline and inline.startswith(f"{P[0].strip()} more words.")


def test_a_named_wrapper_of_the_page_survives():
    got = main_text(f"<body><div class='sidebar'><p>{P[0]}</p>{paras(P[1:])}<div class='ad'>Buy this</div></div><div>Imprint</div></body>")
    assert whole(got) and "Buy" not in got


def test_long_comments_do_not_replace_an_article():
    got = main_text(f"<body><article>{paras(P[:1])}</article><section id='comments'>{paras(P[1:])}</section></body>")
    assert got == P[0].strip()
