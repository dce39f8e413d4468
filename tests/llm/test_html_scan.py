import time

import pytest

from regionfilter.llm import html_text as H

P = "real content words stand in this long paragraph of text, and more of them follow here"
LINKS = "<ul>" + "".join(f"<li><a href=/{i}>link {i}</a></li>" for i in range(8)) + "</ul>"


def everything(page):
    """What would be output without the scan."""
    seen = H.events(page, H.default_weights())
    return " ".join(t for _, t, place in seen if t and place and not place.gone)


@pytest.mark.parametrize(
    "page",
    [
        f"<body><div id=x1><h3>More</h3>{LINKS}</div><div><h1>A title here</h1><p>{P}</p><p>{P}</p></div><div>{LINKS}</div></body>",
        f"<body><table><tr><td>{LINKS}</td><td><p>{P}</p><p>{P}</p></td><td>{LINKS}</td></tr></table></body>",
        f"<body><div><a href=1>one</a> <a href=2>two</a></div><section><div><div><p>{P}</p></div><div><p>{P}</p></div></div></section><div><span>tags</span>{LINKS}</div></body>",
    ],
)
def test_the_scan_decides_without_an_article(page):
    got = H.extract(page)
    assert got.count(P) == 2 and "link" not in got and "link" in everything(page)


def test_the_scan_leaves_out_what_stands_beside_an_article():
    page = f"<body><div><p>{P[:40]}</p></div><article><h1>Title</h1><p>{P}</p><p>{P}</p></article><p>{P[:30]}</p></body>"
    assert H.extract(page) == f"Title\n\n{P}\n\n{P}" and P[:30] in everything(page).replace(P, "")


@pytest.mark.parametrize("name", ["siteHeader", "adBox", "cookieNotice", "shareBar", "commentList", "relatedPosts", "newsletter-signup", "site_footer"])
def test_names_in_any_case_are_read(name):
    page = f"<body><div class=post><p>{P}</p><div class='{name}'><p>not wanted at all</p></div><p>{P}</p></div></body>"
    assert H.extract(page) == f"{P}\n\n{P}"


@pytest.mark.parametrize(
    "inside",
    ["<form><p>fill this in</p><button>Go</button></form>", "<aside>aside words</aside>", "<div class=ad>buy it</div>", "<div role=navigation>menu words</div>", "<div style='display: none'>unseen</div>", "<div class=comments><article class=comment><p>I say so too</p></article></div>", "<nav>a b c</nav>", "<script>x</script>", "<button>press</button>"],
)
def test_furniture_inside_the_article_goes(inside):
    assert H.extract(f"<body><article><p>{P}</p>{inside}<p>{P}</p><ul><li>one item</li><li>two <a href=x>items</a></li></ul></article></body>") == f"{P}\n\n{P}\n\none item\n\ntwo items"


def test_wrappers_and_whole_bodies():
    assert H.extract(f"<body><div class='layout sidebar'><main><p>{P}</p></main></div></body>") == P
    assert H.extract(f"<body><div class='page-with-sidebar'><p>{P}</p></div></body>") == P  # nothing would be left
    assert H.extract(f"<body><form id=aspnet><article><p>{P}</p></article></form></body>") == P
    assert H.extract(f"<body><header class=site><p>site name</p></header><article><header><h1>Title</h1></header><p>{P}</p></article></body>") == f"Title\n\n{P}"
    assert H.extract(f"<p>{P}<p>{P}<div>{P}</div>") == f"{P}\n\n{P}\n\n{P}"


@pytest.mark.parametrize("piece", ["<a ", "<textarea>", '<a ">"', '<a "', "<!-- ", "<div>", "<div></span>", "<script>", "</p>", "<", "<a '", "<li><ul>", "<![CDATA[", "<title>", "<!", "&amp"], ids=repr)
def test_reading_is_linear(piece):
    began = time.time()
    H.extract(piece * (1_000_000 // len(piece)) + f"<p>{P}</p>")
    assert time.time() - began < (40 if piece == "<" or "<div" in piece or "<li" in piece else 20)  # a scan for each piece would take hours


def test_edges(spark):
    rows = [(1, "u", None, "a"), (1, "u", "", "a"), (None, None, f"<p>{P}</p>", "b"), (2, "u", f"<p>{P}</p>", "b"), (2, "u", f"<p>{P}</p>", "b"), (3, "u", "<p>" + "word " * 200_000, None)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string")
    got = sorted((r["page_id"] or 0, r["url"] or "", r["text"], r["n_chars"]) for r in H.extracted(pages).collect())
    long = " ".join(["word"] * 200_000)
    assert got == sorted([(1, "u", "", 0), (1, "u", "", 0), (0, "", P, len(P)), (2, "u", P, len(P)), (2, "u", P, len(P)), (3, "u", long, len(long))])
    assert H.extracted(pages.where("false")).count() == 0
    assert H.extract("<div class=ad>x</div>") in ("", "x") and H.extract("<nav>x</nav>") == ""


def test_weights_can_be_learned_from_other_pages():
    pages = [f"<div class=odd>{MARK}<p>{P}</p>{UNMARK}</div><div class=funny><p>{P}</p></div>" for MARK, UNMARK in [H.MARKS] * 5]
    weights = H.learn(pages)
    assert H.extract(f"<div class=funny><p>{P} not</p></div><div class=odd><p>{P}</p></div>", weights) == P
