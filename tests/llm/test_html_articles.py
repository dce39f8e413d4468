import pytest

from regionfilter.llm import html_text

LONG = " ".join(["real content words"] * 40)


@pytest.mark.parametrize(
    "page",
    [
        f"<body><div class=post><p>{LONG}</p></div><section class=comments><article class=comment>so true</article></section></body>",
        f"<body><script>var t = '<article>';</script><div><p>{LONG}</p></div></body>",
        f"<body><!-- <article> --><div><p>{LONG}</p></div></body>",
        f"<body><div class=post><p>{LONG}</p></div><div id=more><table><tr><td><a href=x>next</a></td></tr></table><article>short tale</article></div></body>",
    ],
)
def test_an_article_elsewhere_does_not_cost_the_body(page):
    assert html_text.extract(page).startswith(LONG)


def test_text_between_articles_inside_the_stretch_stays():
    got = html_text.extract(f"<body><article><p>{LONG}</p></article> a bridge <article><p>{LONG}</p></article></body>")
    assert "a bridge" in got and got.count(LONG) == 2


def test_text_beside_the_article_stays_out():
    assert html_text.extract(f"<body><div><p>{LONG[:90]}</p></div><article><p>{LONG}</p></article><div><p>{LONG[:90]}</p></div></body>") == LONG
