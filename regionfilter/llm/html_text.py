"""HTML extraction by a maximum-scoring subsequence.

A page is read once, from left to right, into texts and tags. Every word of a text scores the log-odds that words in
its place stand in the content: the sum of what its open elements weigh by tag, words of class and id, and role. Tags
score the (negative) log-odds of their kind. All weights are counted on labelled pages (``labelled_pages`` builds
some layouts whose content is marked; ``learn`` takes any such pages). One linear scan finds the contiguous stretch
of highest score, which is the content region, whatever its tags are. Inside the region, elements whose own tag,
classes and role weigh ``GONE`` or less (an advert, a form, a share bar, reader comments) are left out.

Where the article and main elements of a page hold at least as many words as stand beside them (links left out), words
beside them weigh what such words weigh on labelled pages; else the element is a teaser or a comment and is no hint.
A page of which nothing would be left is read again without its class, id and role.

Reading is linear in the page for any input: a tag without its end, a quote without its partner, a comment or a raw
element without its close are each looked for once a page, not once an occurrence.

Output: character references decoded; white space inside a block is one space; blocks in page order, joined by
two line breaks. Nothing is capped: a page of any length is one pass with memory for its own text.

Defined results: null or empty html, or no words that score above zero, give the empty text; unclosed and misnested
tags never fail; repeated pages are rows each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import html
import math
import random
import re
from collections import Counter
from collections.abc import Iterator
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import table

NAME = re.compile(r"/?([a-zA-Z][^\s/>]*)")
STOP = re.compile(r"[>\"']")
ATTRIBUTE = re.compile(r"([a-zA-Z_:][-\w:.]*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
CAMEL = re.compile(r"(?<=[a-z])(?=[A-Z])")
HIDDEN_STYLE = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
# fixed values: names of tags
RAW = frozenset("script style noscript template iframe textarea title xmp".split())
NO_TEXT = frozenset("svg object video audio canvas math select option datalist".split()) | RAW
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
#: an opening tag of these closes an open element of the same group inside the nearest of the named ones
SIBLINGS = {"li": (("li",), ("ul", "ol", "menu")), "dt": (("dt", "dd"), ("dl",)), "dd": (("dt", "dd"), ("dl",)), "td": (("td", "th"), ("tr", "table")), "th": (("td", "th"), ("tr", "table")), "tr": (("tr",), ("table",))}
COMMENTS = frozenset("comment comments disqus reply replies respond responses".split())
#: own log-odds at which an element is left out of the region, and the most that a word or a tag can score
GONE, MOST = -3.0, 3.0
#: fewer words than these say nothing of a tag inside articles
RARE = 100
#: marks around the content of a labelled page
MARKS = ("<!--[-->", "<!--]-->")


class Place:
    """What is known of a text's place: the features of its open elements, their weight, and whether it is left out."""

    __slots__ = ("features", "weight", "gone", "firm", "article", "link", "inner")

    def __init__(self, features: frozenset = frozenset(), weight: float = 0.0, gone: bool = False, firm: bool = False, article: bool = False, link: bool = False):
        self.features, self.weight, self.gone, self.firm, self.article, self.link = features, weight, gone, firm, article, link
        self.inner: dict[tuple[str, str], Place] = {}


def own_features(tag: str, source: str, outer: Place, named: bool = True) -> frozenset:
    """Features of an element: its tag (with 'in ' inside an article or main element), class and id words, role."""
    found = {("in " if outer.article and tag not in ("article", "main") else "") + tag}
    if tag == "a" and ("li" in outer.features or "in li" in outer.features):
        found.add("li a")
    if named and source.strip("/ \t\r\n\f"):
        a = {m[1].lower(): html.unescape(m[2] or m[3] or m[4] or "") for m in ATTRIBUTE.finditer(source)}
        for names in (a.get("class", ""), a.get("id", "")):
            found.update("." + w for w in re.split(r"[^a-z]+", CAMEL.sub("-", names).lower()) if len(w) > 1)
        if role := a.get("role", "").strip().lower():
            found.add("role " + role)
        if "hidden" in a or a.get("aria-hidden", "").lower() == "true" or HIDDEN_STYLE.search(a.get("style", "")):
            found.add("hidden")
    return frozenset(found)


class Weights:
    """Log-odds of standing in the content, of features and of tags, by counts on labelled pages."""

    def __init__(self, words: tuple[Counter, Counter], tags: tuple[Counter, Counter], seen: tuple[int, int]):
        (inside, outside), (tags_in, tags_out), (n_in, n_out) = words, tags, seen
        self.feature = {f: _odds(inside[f], outside[f], n_in, n_out) for f in {*inside, *outside}}
        for tag in {*tags_in, *tags_out}:  # what was hardly seen inside an article weighs what it weighs elsewhere
            if inside[f"in {tag}"] + outside[f"in {tag}"] < RARE:
                self.feature[f"in {tag}"] = self.feature.get(tag, 0.0)
        self.prior = math.log((n_in + 1) / (n_out + 1))
        all_in, all_out = sum(tags_in.values()), sum(tags_out.values())
        self.tag = {t: max(-MOST, min(-0.05, _odds(tags_in[t], tags_out[t], all_in, all_out))) for t in {*tags_in, *tags_out}}
        self.other_tag = -0.5
        self.places, self.roots = 0, {True: Place(), False: Place()}

    def root(self, named: bool) -> Place:
        """The place outside all elements; places are remembered from page to page up to a number."""
        if self.places > 20_000:
            self.places, self.roots = 0, {True: Place(), False: Place()}
        return self.roots[named]

    def enter(self, outer: Place, tag: str, source: str, named: bool) -> Place:
        """The place inside an element."""
        found = outer.inner.get((tag, source))
        if found is None:
            own = own_features(tag, source, outer, named)
            weigh = self.feature.get
            # a bare tag never speaks for an element whose name speaks against it, and inline tags only count for words
            bare = sum(min(0.0, weigh(f, 0.0)) for f in own if not _named(f)) if tag in BLOCKS or tag == "button" else 0.0
            gone = tag in NO_TEXT or bare + sum(weigh(f, 0.0) for f in own if _named(f)) <= GONE
            anew = tag in ("article", "main") and outer.gone and not outer.firm and not gone
            if anew:  # a wrapper around the article is no furniture, whatever its name
                features, gone = own, False
            else:
                features = outer.features | own
                gone = gone or outer.gone
            reader = any(f[1:] in COMMENTS for f in own if f[0] == ".")
            firm = gone and (outer.firm or tag in ("aside", "footer") or "hidden" in own or reader)
            article, link = (outer.article or tag in ("article", "main") and not reader) and not gone, outer.link and tag not in BLOCKS or tag == "a"
            if (features, gone, firm, article, link) == (outer.features, outer.gone, outer.firm, outer.article, outer.link):
                return outer  # however deep elements nest, their places are few
            found = Place(features, sum(weigh(f, 0.0) for f in features), gone, firm, article, link)
            if len(source) < 200:
                outer.inner[(tag, source)] = found
                self.places += 1
        return found

    def word(self, place: Place, beside: bool) -> float:
        x = self.prior + place.weight + (self.feature.get("beside", 0.0) if beside and not place.article else 0.0)
        return max(-MOST, min(MOST, x))


def _named(feature: str) -> bool:
    return feature[0] == "." or feature == "hidden" or feature.startswith("role ")


def _odds(inside: int, outside: int, all_in: int, all_out: int) -> float:
    return math.log((inside + 0.5) / (all_in + 1)) - math.log((outside + 0.5) / (all_out + 1))


def events(page: str, weights: Weights, named: bool = True) -> list[tuple[str, str, Place | None]]:
    """(tag, text, place) in page order. Texts have no tag and their place; tags are 'NAME', with '+' before it if they
    begin or end a block. An element that is left out is one tag, and the tags inside it are none. 'mark' stands for the
    marks of labelled pages."""
    out: list[tuple[str, str, Place | None]] = []
    root = weights.root(named)
    stack: list[tuple[str, Place]] = []
    open_at: dict[str, list[int]] = {}
    blocks: list[int] = []  # where open block elements lie in the stack
    here, at, size = root, 0, len(page)
    last_end = page.rfind(">")
    quotes, ends = True, {}  # ends: raw tags whose close is known not to come

    def leave(down_to: int) -> None:
        nonlocal here
        while len(stack) > down_to:
            open_at[stack.pop()[0]].pop()
        while blocks and blocks[-1] >= down_to:
            blocks.pop()
        here = stack[-1][1] if stack else root

    def last(*tags: str) -> int:
        return max((open_at[t][-1] for t in tags if open_at.get(t)), default=-1)

    while at < size:
        begin = page.find("<", at)
        if begin < 0 or begin > last_end:  # no tag can end any more
            out.append(("", page[at:], here))
            break
        if begin > at:
            out.append(("", page[at:begin], here))
        m = NAME.match(page, begin + 1)
        if m is None:
            if page.startswith("<!--", begin):
                end = page.find("-->", begin + 4)
                end = size if end < 0 else end + 3
                if page[begin:end] in MARKS:
                    out.append(("mark", "", None))
            elif page.startswith("<![CDATA[", begin):
                end = page.find("]]>", begin)
                out.append(("", page[begin + 9 : size if end < 0 else end], here))
                end = size if end < 0 else end + 3
            elif page[begin + 1 : begin + 2] in ("!", "?", "/"):
                end = page.find(">", begin) + 1
            else:
                out.append(("", "<", here))
                end = begin + 1
            at = end
            continue
        end = m.end()
        while True:  # the tag's end: a '>' outside quotes
            stop = STOP.search(page, end)
            if stop is None:
                quotes, end = False, page.find(">", m.end()) + 1  # last_end lies ahead, inside quotes: they are broken
                break
            end = stop.end()
            if stop[0] == ">":
                break
            if quotes:
                pair = page.find(stop[0], end)
                if pair < 0:
                    quotes = False
                else:
                    end = pair + 1
        tag, source, closes = m[1].lower(), page[m.end() : end - 1], page[begin + 1] == "/"
        at = end
        if closes:
            where, was_gone = open_at.get(tag), here.gone
            if where and tag not in ("body", "html") and (tag in BLOCKS or not blocks or blocks[-1] < where[-1]):
                leave(where[-1])
            if not here.gone:
                out.append(("+" if was_gone else "+" + tag if tag in BLOCKS else tag, "", None))
            continue
        if tag in VOID:
            if not here.gone:
                out.append(("+" + tag if tag in BLOCKS else tag, " " if tag == "br" else "", here))
            continue
        if tag in RAW:  # its content is no markup
            if tag not in ends:
                close = re.compile(rf"</{tag}(?=[\s/>])[^>]*>", re.I).search(page, at)
                if close is None:
                    ends[tag] = True
                    at = size if tag in ("script", "style") else at
                else:
                    at = close.end()
            if not here.gone:
                out.append((tag, "", None))
            continue
        if tag in BLOCKS:
            if tag == "body" and open_at.get("head"):
                leave(open_at["head"][0])
            if (p := last("p")) > last("td", "th", "button", "object"):
                leave(p)
            if tag in SIBLINGS and (b := last(*SIBLINGS[tag][0])) > last(*SIBLINGS[tag][1]):
                leave(b)
        if tag == "a" and (a := last("a")) >= 0 and not (blocks and blocks[-1] > a):
            leave(a)
        if not here.gone or tag in ("article", "main"):
            out.append(("+" + tag if tag in BLOCKS else tag, "", None))
        if not source.endswith("/") or tag in BLOCKS:
            here = weights.enter(here, tag, source, named)
            open_at.setdefault(tag, []).append(len(stack))
            if tag in BLOCKS:
                blocks.append(len(stack))
            stack.append((tag, here))
    return out


def beside(seen: list[tuple[str, str, Place | None]]) -> bool:
    """Whether the page's article and main elements hold at least as many words as stand beside them."""
    held = other = 0
    for tag, text, place in seen:
        if place is not None and not tag and not place.gone:
            if place.article:
                held += len(text.split())
            elif not place.link:
                other += len(text.split())
    return held > 0 and held >= other


def scores(seen: list[tuple[str, str, Place | None]], weights: Weights) -> list[float]:
    """The score of each event."""
    hint, out = beside(seen), []
    for tag, text, place in seen:
        if place is not None and text:
            n = len(text.split())
            x = n * weights.word(place, hint) if n else 0.0
            out.append(max(-MOST, min(0.0, x)) if place.gone else x)  # what is left out is a gap, however long
        else:
            tag = tag.lstrip("+")
            out.append(0.0 if tag in ("", "mark") else weights.tag.get(tag, weights.other_tag))
    return out


def best_stretch(scores: list[float]) -> tuple[int, int]:
    """[begin, end) of the neighbours with the largest sum; of equal sums the longest from the earliest start."""
    best, best_at, total, begin = 0.0, (0, 0), 0.0, 0
    for i, s in enumerate(scores):
        if total < 0:
            total, begin = 0.0, i
        total += s
        if total > best or total == best and best_at[1] and begin == best_at[0]:
            best, best_at = total, (begin, i + 1)
    return best_at


def extract(page: str | None, weights: Weights | None = None) -> str:
    """The main text of a page."""
    weights = weights or default_weights()
    for named in (True, False):
        seen = events(page or "", weights, named)
        begin, end = best_stretch(scores(seen, weights))
        blocks, open_ = [], []
        for tag, text, place in [*seen[begin:end], ("+", "", None)]:
            if tag[:1] == "+":
                blocks.append("".join(open_))
                open_ = []
            if text and not place.gone:
                open_.append(html.unescape(text))
        blocks = [" ".join(b.split()) for b in blocks]
        text = "\n\n".join(b for b in blocks if b)
        if text or not page:
            return text
    return ""


def learn(pages: list[str]) -> Weights:
    """Weights from pages whose content stands between marks."""
    words, tags, seen = (Counter(), Counter()), (Counter(), Counter()), [0, 0]
    blank = Weights(words, tags, (0, 0))
    for page in pages:
        outside, found = 1, events(page, blank)
        hint = beside(found)
        for tag, text, place in found:
            if tag == "mark":
                outside = 1 - outside
            elif place is not None and text:
                n = len(text.split())
                seen[outside] += n
                for f in [*place.features, *(["beside"] if hint and not place.article else [])]:
                    words[outside][f] += n
            elif tag.strip("+"):
                tags[outside][tag.lstrip("+")] += 1
    return Weights(words, tags, (seen[0], seen[1]))


# fixed values: names that sites give to what is and what is not content; the labelled pages carry them
FURNITURE_NAMES = (
    "ad ads adv advert advertisement advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus disclaimer dropdown footer gdpr login masthead menu modal nav navbar navigation newsletter "
    "notice notices notification overlay pager pagination paywall popup promo promoted promotion recommended related reply replies respond responses search share sharing sidebar signin signup skip social sponsor sponsored "
    "subscribe subscription tagcloud teaser toolbar topbar widget"
).split()
FURNITURE_ROLES = "navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar".split()
CONTENT_NAMES = "article content entry main post story body text page prose".split()


def labelled_pages(n: int = 120, seed: int = 5) -> list[str]:
    """Pages of many layouts, whose content stands between marks."""
    draw = random.Random(seed)
    vocabulary = "the river runs past old mills and quiet fields where children learn to swim each summer before school".split()
    say = lambda low, high: " ".join(draw.choice(vocabulary) for _ in range(draw.randint(low, high)))
    links = lambda k: "<ul>" + "".join(f'<li><a href="/{i}">{say(1, 2)}</a></li>' for i in range(k)) + "</ul>"
    out_of = lambda x: f"{MARKS[1]}{x}{MARKS[0]}"
    names, roles = [*FURNITURE_NAMES, *["header"] * 3] * 5, FURNITURE_ROLES * 5
    draw.shuffle(names)
    draw.shuffle(roles)

    def box() -> str:
        """Something that is no content, under the next name or role."""
        inner = draw.choice([lambda: f"<p>{say(6, 25)}</p>", lambda: links(4), lambda: say(4, 15), lambda: f"<h3>{say(1, 3)}</h3>{links(3)}", lambda: f"<div><span>{say(2, 9)}</span></div>"])()
        kind = draw.randrange(10)
        if kind < 6 and names:
            name = names.pop()
            return f"<{(t := draw.choice(['div', 'div', 'section', 'article' if name in COMMENTS else 'div']))} {draw.choice(['class', 'id'])}=\"{draw.choice([name, 'site-' + name, name + ' x1'])}\">{inner}</{t}>"
        if kind == 6 and roles:
            return f'<div role="{roles.pop()}">{inner}</div>'
        if kind == 7:
            return f"<div {draw.choice(['hidden', 'aria-hidden=true', 'style=display:none'])}>{inner}</div>"
        tag = draw.choice(["aside", "form", "dialog", "button", "menu", "nav"])
        return f"<{tag}>{inner if tag != 'button' else say(1, 2)}</{tag}>"

    def part() -> str:
        return draw.choice(
            [lambda: f"<p>{say(20, 60)} <a href=x>{say(1, 3)}</a> {say(5, 20)}.</p>"] * 5
            + [lambda: f"<p>{say(5, 40)}<br>{say(3, 20)}</p>", lambda: f"<h2>{say(2, 6)}</h2>", lambda: f"<blockquote>{say(8, 30)}</blockquote>", lambda: "<ul>" + "".join(f"<li>{say(3, 14)}</li>" for _ in range(3)) + "</ul>"]
            + [lambda: f"<ol><li><p>{say(6, 20)}</p></li><li>{say(4, 9)} <a href=y>{say(1, 2)}</a></li></ol>", lambda: f"<p><b>{say(3, 8)}</b> <i>{say(2, 5)}</i> {say(9, 30)}</p>", lambda: f"<figure><img src=x><figcaption>{say(4, 12)}</figcaption></figure>"]
            + [lambda: f"<ul><li><a href=x>{say(3, 8)}</a></li><li>{say(6, 12)} <a href=x>{say(2, 3)}</a> <span>{say(2, 8)}</span></li></ul>", lambda: f"<p><span>{say(9, 30)}</span> <a href=v>{say(3, 9)}</a></p>"] * 2
            + [lambda: f"<dl><dt>{say(1, 3)}</dt><dd>{say(6, 20)}</dd></dl>", lambda: f"<details><summary>{say(2, 5)}</summary>{say(9, 30)}</details>", lambda: f"<h4>{say(2, 5)}</h4>{say(9, 30)}"]
            + [lambda: f"<table><tr><th>{say(1, 2)}</th><td>{say(1, 4)}</td></tr><tr><td>{say(1, 4)}</td><td>{say(1, 4)}</td></tr></table>", lambda: f"<pre><code>{say(4, 16)}</code></pre>", lambda: f"<div><p>{say(15, 50)}</p></div>", lambda: f"<section><h3>{say(2, 4)}</h3><p>{say(20, 50)}</p></section>"]
        )()

    pages = []
    for k in range(n):
        body = "".join(part() + (out_of(box()) if draw.random() < 0.2 else "") for _ in range(draw.randint(3, 9)))
        head = draw.choice([f"<h1>{say(2, 8)}</h1>", f"<header><h1>{say(2, 8)}</h1><p>{say(3, 9)}</p></header>", f"<div class=\"{draw.choice(CONTENT_NAMES)}-header\"><h1>{say(3, 8)}</h1></div>"])
        if k % 6 >= 2:
            head = head.replace("<header>", "<div>").replace("</header>", "</div>")
        content = f"{MARKS[0]}{head}{body}{MARKS[1]}"
        name = CONTENT_NAMES[k % len(CONTENT_NAMES)]
        content = [f"<article>{content}</article>", f'<main><div class="{name}">{content}</div></main>', f'<div class="{name}">{content}</div>', f"<div>{content}</div>", f'<div id="{name}-{k}"><section>{content}</section></div>', f"<table><tr><td>{links(4)}</td><td>{content}</td><td><a href=x>{say(1, 2)}</a></td></tr></table>"][k % 6]
        plain = lambda: f"<div><h3>{say(1, 3)}</h3>{links(5)}</div><div><span>{say(1, 6)}</span> <a href=z>{say(1, 3)}</a></div>" + (f"<p>{say(4, 14)}</p>" if k % 6 < 2 else "")  # noqa: E731, B023
        comments = f'<section class="comments">{"".join(f"<article class=comment><p>{say(8, 40)}</p></article>" for _ in range(3))}</section>' if k % 2 else f'<div id="comments"><h3>{say(1, 2)}</h3><div class="comment"><p>{say(10, 30)}</p></div></div>'
        top = f"<header><div>{say(1, 4)}</div><nav>{links(6)}</nav></header>" if k % 3 else f"<nav>{links(6)}</nav>"
        pages.append(
            f"<html><head><title>{say(2, 6)}</title></head><body>{top}{box()}{plain()}{content}{box()}{comments if draw.random() < 0.6 else ''}{plain()}{box()}"
            f"<table><tr><td><a href=x>{say(1, 2)}</a></td><td><a href=w>{say(1, 2)}</a></td></tr></table><footer><p>{say(4, 16)}</p></footer></body></html>"
        )
    return pages


@cache
def default_weights() -> Weights:
    return learn(labelled_pages())


def extracted(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) for every row of pages."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts = [extract(h) for h in b.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column("page_id"), b.column("url"), pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op3_html_text(spark, sf_dir: str) -> DataFrame:
    return extracted(table(spark, sf_dir, "pages"))
