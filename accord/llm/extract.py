"""Main text of web pages.

The standard library's parser streams events; text between two block tags is a line. Each line has a text-to-tag ratio; the logarithms of the ratios are smoothed by a
Gaussian and split into two clusters. Lines of the high cluster speak for the elements that hold them, by their letters, and those of the low one against; the
regions are the elements apart from each other that have most in all. A region that lies in an article or main element, or holds such elements with most of
its high lines, stands for these. All lines of a region are kept, low ones too, but for those in menus, headers, footers, sidebars, notices, adverts, forms,
scripts, styles and reader comments within it, told by element, role, or whole names of class and id.

Nulls: null or empty html gives an empty text; malformed markup is read as far as the parser can, with odd declarations taken for comments. A null id or url
stays null. Pages are parsed whole; repeated rows give equal texts. Line breaks (br) are white space of their block. An empty table gives no rows. Other columns of
the input aren't read.
"""

from __future__ import annotations

import math
import re
from html.parser import HTMLParser

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from accord.llm.common import table

#: Elements by their part in a page.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre search section select summary table tbody td tfoot th thead title tr ul".split())
#: Elements that can be regions.
REGIONS = frozenset("article aside body center details dialog div footer form header main nav section table td".split())
#: Elements whose text no page shows, and those that are furniture.
UNSEEN = frozenset("applet audio canvas datalist embed frame frameset head iframe map noembed noframes noscript object script style svg template textarea title video".split())
FURNITURE = frozenset("aside button dialog footer form input label legend menu nav option search select".split())
HEADING = frozenset("h1 h2 h3 h4 h5 h6".split())
MAIN = frozenset("article main".split())
#: An open element of the first kind ends where one of the others begins.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr"}, "td": {"td", "th", "tr"}, "th": {"td", "th", "tr"}, "option": {"option"}}
LIMITS = frozenset("ul ol dl table article section div body main".split())
ROLES = frozenset("alert alertdialog banner complementary contentinfo dialog form menu menubar navigation search toolbar".split())
#: Whole names of class and id of what isn't content, alone or with a word before or after them that says where or what shape they are.
NAMES = frozenset("ad ads adsense advert adverts advertisement advertisements banner breadcrumb breadcrumbs comment comments cookie cookies consent copyright disclaimer disqus_thread footer gdpr infobar menu modal nav navbar navigation newsletter notice notification overlay pager pagination paywall popup promo promotion recommended related respond share sharing sidebar signup skip-link social sponsored subscribe toolbar topbar trending widget widgets".split())
BEFORE = ("site", "page", "main", "global", "top", "bottom", "left", "right", "side", "user", "reader", "article", "post", "blog", "social", "cookie", "gdpr", "newsletter", "mobile", "primary", "secondary", "sub")
AFTER = ("bar", "box", "block", "banner", "slot", "unit", "list", "links", "buttons", "icons", "container", "wrapper", "area", "section", "content", "form", "item", "items", "body", "text", "notice", "message", "popup", "modal", "posts", "articles", "menu")
_NAME = re.compile(r"[^\s]+")
#: A further region needs this share of the best one's letters in lines of the high cluster.
FURTHER = 0.1
#: Elements of a single line each are paragraphs of the one around them if that has this share of what they have.
MERGE = 0.8


def _named(name: str) -> bool:
    name = re.sub(r"(?<=[a-z])(?=[A-Z])", "-", name).lower().replace("_", "-").strip("-")
    if name in NAMES or name.replace("-", "_") in NAMES:
        return True
    parts = name.split("-")
    return len(parts) == 2 and (parts[0] in BEFORE and parts[1] in NAMES or parts[0] in NAMES and parts[1] in AFTER) or len(parts) == 3 and parts[0] in BEFORE and parts[1] in NAMES and parts[2] in AFTER


def _furniture(tag: str, attrs: dict) -> bool:
    if tag in FURNITURE:
        return True
    if "hidden" in attrs or (attrs.get("aria-hidden") or "").lower() == "true" or (attrs.get("role") or "").lower() in ROLES:
        return True
    if re.search(r"display\s*:\s*none", attrs.get("style") or "", re.I):
        return True
    if tag in ("html", "body", "main") or tag in HEADING:
        return False
    names = _names(attrs)
    if tag == "article":
        return any(n.lower() in ("comment", "comments", "reply") for n in names)
    return any(map(_named, names))


def _names(attrs: dict) -> list[str]:
    return _NAME.findall(f"{attrs.get('class') or ''} {attrs.get('id') or ''}")


class _Lines(HTMLParser):
    """Collects lines: (text, without furniture, tags, heading, place of the innermost region); regions have a parent and a tag."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.stack: list[list] = []  # tag, unseen, furniture, region
        self.lines: list[tuple] = []
        self.regions: list[tuple] = [(-1, "")]  # the page itself
        self.text: list[str] = []
        self.kept: list[str] = []
        self.tags = self.unseen = self.furniture = self.main = self.headings = 0

    def end_line(self) -> None:
        text = " ".join("".join(self.text).split())
        if text:
            self.lines.append((text, " ".join("".join(self.kept).split()), self.tags, self.headings > 0, self.stack[-1][3] if self.stack else 0))
            self.tags = 0
        self.text, self.kept = [], []

    def pop_to(self, i: int) -> None:
        if any(x[0] in BLOCK for x in self.stack[i:]):
            self.end_line()
        for tag, unseen, furniture, _ in self.stack[i:]:
            self.unseen -= unseen
            self.furniture -= furniture
            self.main -= tag in MAIN
            self.headings -= tag in HEADING
        del self.stack[i:]

    def handle_starttag(self, tag, attrs) -> None:
        self.tags += 1
        if tag == "br":
            self.handle_data(" ")
            return
        if tag in VOID:
            if tag == "hr":
                self.end_line()
            return
        if tag in BLOCK:
            self.end_line()
            for i in range(len(self.stack) - 1, -1, -1):
                name = self.stack[i][0]
                if tag in ENDS.get(name, ()) or name == "p":
                    self.pop_to(i)
                    break
                if name in LIMITS:
                    break
        attrs = dict(attrs)
        furniture = _furniture(tag, attrs)
        if not furniture and not self.main and (tag == "header" or tag not in HEADING and tag not in ("html", "body", *MAIN) and any(n.lower() in ("header", "masthead", "site-header", "page-header") for n in _names(attrs))):
            furniture = True  # an article's own header has its title
        region = self.stack[-1][3] if self.stack else 0
        if tag in REGIONS:
            self.regions.append((region, tag))
            region = len(self.regions) - 1
        self.stack.append([tag, tag in UNSEEN, furniture, region])
        self.unseen += tag in UNSEEN
        self.furniture += furniture
        self.main += tag in MAIN
        self.headings += tag in HEADING

    def handle_startendtag(self, tag, attrs) -> None:
        self.handle_starttag(tag, attrs)
        if tag not in VOID and self.stack and self.stack[-1][0] == tag and tag in ("svg", "path", "iframe", "use"):
            self.pop_to(len(self.stack) - 1)

    def handle_endtag(self, tag) -> None:
        self.tags += 1
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == tag:
                self.pop_to(i)
                return
            if tag not in BLOCK and self.stack[i][0] in BLOCK:
                return

    def handle_data(self, data) -> None:
        if not self.unseen:
            self.text.append(data)
            if not self.furniture:
                self.kept.append(data)

    def parse_marked_section(self, i, report=1):
        return self.parse_bogus_comment(i)

    def unknown_decl(self, data) -> None:
        """Odd declarations have no text."""


def smoothed(x: list[float], sigma: float = 0.6) -> list[float]:
    radius = math.ceil(3 * sigma)
    kernel = [math.exp(-k * k / (2 * sigma * sigma)) for k in range(-radius, radius + 1)]
    out = []
    for i in range(len(x)):
        near = [(kernel[k + radius], x[i + k]) for k in range(-radius, radius + 1) if 0 <= i + k < len(x)]
        out.append(sum(w * v for w, v in near) / sum(w for w, _ in near))
    return out


def threshold(x: list[float]) -> float:
    """Between the means of two clusters of numbers."""
    low, high = min(x), max(x)
    for _ in range(20):
        cut = (low + high) / 2
        a, b = [v for v in x if v <= cut], [v for v in x if v > cut]
        if not a or not b:
            return cut if b else low - 1
        after = (sum(a) / len(a), sum(b) / len(b))
        if after == (low, high):
            break
        low, high = after
    return (low + high) / 2


def ratios(lines: list[tuple]) -> list[float]:
    return [math.log1p(len(text) / max(1, tags)) for text, _, tags, *_ in lines]


def chosen(lines: list[tuple], regions: list[tuple]) -> list[int]:
    """The regions of the page, by the clusters of the smoothed ratios of its lines."""
    level = smoothed(ratios(lines))
    cut = threshold(level)
    high, total, own, count = ([0] * len(regions) for _ in range(4))
    for r, (text, kept, _, heading, at) in zip(level, lines):
        count[at] += 1
        if r > cut:
            high[at] += len(kept)
            total[at] += len(kept)
        elif not heading:
            total[at] -= len(text)
    best, parts = total, [[] for _ in regions]  # of the elements inside: what they bring in all if taken apart, and which
    apart = [0] * len(regions)
    for k in range(len(regions) - 1, -1, -1):
        if best[k] <= 0 and apart[k] <= 0:
            own[k], taken = 0, []
        elif best[k] >= apart[k] or best[k] >= MERGE * apart[k] and len(parts[k]) > 1 and all(count[j] == 1 for j in parts[k]):
            own[k], taken = best[k], [k]
        else:
            own[k], taken = apart[k], parts[k]
        up = regions[k][0]
        if up >= 0:
            best[up] += best[k]
            high[up] += high[k]
            count[up] += count[k]
            apart[up] += own[k]
            parts[up] = parts[up] + taken if len(parts[up]) > len(taken) else taken + parts[up]
        else:
            out = taken
    if not out:  # low lines outweigh the others everywhere: the least element with all the high ones
        out = [max((k for k in range(len(regions)) if high[k] == high[0]), default=0)]
    most = max(high[k] for k in out)
    return _widened([k for k in out if high[k] >= FURTHER * most], regions, high)


def _widened(out: list[int], regions: list[tuple], high: list[int]) -> list[int]:
    """Article or main elements in the place of regions that lie in them or hold little else."""
    holder: list[int | None] = []  # the nearest article around, or else main
    last = list(range(len(regions)))  # the last region inside; regions are numbered as they open
    for k, (up, tag) in enumerate(regions):
        around = holder[up] if up >= 0 else None
        holder.append(k if tag == "article" or tag == "main" and around is None else around)
    for k in range(len(regions) - 1, 0, -1):
        last[regions[k][0]] = max(last[regions[k][0]], last[k])
    outer = [k for k, (up, _) in enumerate(regions) if holder[k] == k and holder[up] is None]
    new: list[int] = []
    for k in out:
        held = [j for j in outer if k < j <= last[k] and high[j]]
        if holder[k] is not None:
            new.append(holder[k])
        elif held and sum(high[j] for j in held) >= 0.8 * high[k]:
            new += held
        else:
            new.append(k)
    return new


def main_text(html: str | None) -> str:
    page = _Lines()
    page.feed(html or "")
    page.close()
    page.pop_to(0)
    page.end_line()
    if not page.lines:
        return ""
    inside = [False] * len(page.regions)
    for k in chosen(page.lines, page.regions):
        inside[k] = True
    for k in range(1, len(page.regions)):
        inside[k] = inside[k] or inside[page.regions[k][0]]
    return "\n".join(kept for _, kept, _, _, at in page.lines if inside[at] and kept)


def extracted(pages: DataFrame, key: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """(key, url, text)."""
    names = [key, url]

    def run(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array([main_text(h) for h in b.column(2).to_pylist()], pa.string())], names=[*names, "text"])

    schema = ", ".join(f"`{c}` {pages.schema[c].dataType.simpleString()}" for c in names)
    return pages.select(*[F.col(f"`{c}`") for c in (key, url, html)]).mapInArrow(run, f"{schema}, text string")


def op6_extract(spark, sf_dir: str) -> DataFrame:
    return extracted(table(spark, sf_dir, "pages", "page_id", "url", "html")).withColumn("n_chars", F.length("text").cast("long"))
