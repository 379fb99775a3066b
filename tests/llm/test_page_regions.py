"""Main text of pages whose tags and names do not point at it."""

from kernmill.llm.html_text import main_text

P = [f"Paragraph {i} tells a good part of the story, in whole sentences and without a link. " * 3 for i in range(8)]


def paras(texts):
    return "".join(f"<p>{t}</p>" for t in texts)


def whole(got, texts=P):
    lines = got.split("\n")
    return all(t.strip() in lines for t in texts)


def test_teaser_articles_do_not_hide_the_story():
    cards = "".join(f"<article><h3><a href=x>Card {i}</a></h3><p><a href=x>See more</a></p></article>" for i in range(4))
    got = main_text(f"<body><div id=story><h1>Title</h1>{paras(P)}</div><div class=cards>{cards}</div></body>")
    assert whole(got) and got.startswith("Title") and "Card" not in got


def test_sibling_articles_all_come_back():
    assert whole(main_text(f"<body><div><article>{paras(P[:6])}</article><article>{paras(P[6:])}</article></div></body>"))


def test_sections_without_article_all_come_back():
    assert whole(main_text(f"<body><div><div>{paras(P[:7])}</div><div>{paras(P[7:])}</div></div></body>"))
    assert whole(main_text(f"<body><section>{paras(P[:1])}</section><section>{paras(P[1:7])}</section><section>{paras(P[7:])}</section></body>"))


def test_text_outside_the_article_stays_if_as_dense():
    assert whole(main_text(f"<body><article>{paras(P[:7])}</article><div>{paras(P[7:])}</div></body>"))
    assert main_text(f"<body><article>{paras(P)}</article><div>Imprint of the site, with some words.</div></body>") == "\n".join(t.strip() for t in P)
