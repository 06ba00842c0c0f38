"""Text-to-tag ratios decide what is content: pages without telling names, several articles, look-alike names and malformed markup."""

import html as H
import random
import re

import pytest

from accord.llm import extract
from conftest import SF

PROSE = "A paragraph of plain words that goes on for long enough to be taken for content, with a second clause, and a third one too. "


def truth(html):
    inner = re.search(r"<article>(.*?)</article>", html, re.S)[1].replace("<br>", " ")
    parts = [" ".join(H.unescape(re.sub(r"<[^>]+>", "", x)).split()) for x in re.split(r"</?(?:p|h1)\b[^>]*>", inner)]
    return "\n".join(x for x in parts if x)


def bare(html):
    """The page with no element or name that tells what a part is."""
    return re.sub(r"(</?)(article|nav|footer)\b", r"\1div", html).replace(' class="ad"', "")


@pytest.fixture(scope="module")
def pages(spark):
    return [r.html for r in spark.read.parquet(f"{SF.replace('0.001', '0.01')}/pages.parquet").collect()]


def test_given_pages_without_article_elements(pages):
    assert all(extract.main_text(h.replace("article>", "div>")) == truth(h) for h in pages)


def test_ratios_decide(pages, monkeypatch):
    right = sum(extract.main_text(bare(h)) == truth(h) for h in pages)
    assert right >= 0.7 * len(pages)
    monkeypatch.setattr(extract, "ratios", lambda lines: [1.0] * len(lines))
    assert sum(extract.main_text(bare(h)) == truth(h) for h in pages) <= 0.1 * right


def test_clusters_against_plain_means():
    random.seed(1)
    for _ in range(50):
        x = [random.random() for _ in range(8)] + [5 + random.random() for _ in range(8)]
        best = min(sorted(x)[:-1], key=lambda c: sum((v - sum(p) / len(p)) ** 2 for p in ([a for a in x if a <= c], [a for a in x if a > c]) for v in p))
        assert sorted(v > extract.threshold(x) for v in x) == sorted(v > best for v in x)


@pytest.mark.parametrize(
    ("html", "want"),
    [
        (f"<body><div><a href=1>Home</a> <a href=2>News</a></div><article><p>{PROSE}</article><div><a>x</a><a>y</a></div><article><p>Second. {PROSE}</article>", f"{PROSE.strip()}\nSecond. {PROSE.strip()}"),
        (f"<div class='social-science'><article><p>{PROSE}</article></div>", PROSE.strip()),
        (f"<article><p>{PROSE}</p><p><a href=x>A paragraph that is wholly a link</a></p><p>{PROSE}</p></article>", f"{PROSE.strip()}\nA paragraph that is wholly a link\n{PROSE.strip()}"),
        (f"<article><p>{PROSE}</p><section id=related-work><h2>Related work</h2><p>{PROSE}</p></section></article>", f"{PROSE.strip()}\nRelated work\n{PROSE.strip()}"),
        (f"<article><p>{PROSE}</p><div class=comments><p>First! {PROSE * 9}</p></div></article>", PROSE.strip()),
        (f"<div><div>{'<a href=x>go</a> ' * 9}</div><div><h1>Head</h1><p>{PROSE}</p><p>Short.</p><p>{PROSE}</p></div><div>{'<a href=x>go</a> ' * 9}</div></div>", f"Head\n{PROSE.strip()}\nShort.\n{PROSE.strip()}"),
        (f"<p>{PROSE}</p><![foo[<p>after it</p><![CDATA[x]]><![if !IE]>{PROSE}", f"{PROSE.strip()}\nafter it{PROSE.strip()}"),
    ],
)
def test_regions(html, want):
    assert extract.main_text(html) == want


def test_any_markup_is_read():
    random.seed(2)
    parts = ["<", "<!", "<![", "<!--", "-->", "]]>", ">", "</", "p", "div ", "foo[", "&", "&#x", "'", '"', "=", "script", "<p>", "</p>", "<a ", "?", " ", "<!doctype", "<svg/>", "CDATA[", "if ", "word"]
    for _ in range(5000):
        assert isinstance(extract.main_text("".join(random.choices(parts, k=random.randrange(14)))), str)
    assert len(extract.main_text("<div>" * 3000 + "deep " + "<p>" * 3000 + PROSE * 500)) > 500 * len(PROSE) - 5
