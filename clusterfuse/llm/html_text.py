"""Main text of web pages by consensus paths of their hosts.

Each page scores its containers by the text that they and all containers in them hold (length and commas, less links).
Its best container is the smallest that surrounds all running text; it casts a vote, weighed by its share of the page's
score, for its path: the tags and classes from the root with digits generalised. Votes are added up in Spark for each
host, and pages are then read again with the winning paths of their host: all containers of the first winner that holds
text on the page give the text in page order, else the page's own best container does.

Dropped: scripts, styles and hidden parts; menus, headers, footers, sidebars, dialogs by tag and role (the header of an
article that holds a heading stays); and parts whose class or id names them as furniture (menus, sidebars, notices,
adverts, shares, reader comments, ...) and forms. A name alone never decides against the text: a named part or a form
that holds the page's top heading or more than half of its score is no furniture (reader comments excepted), and where
nothing else is left on a page, names are passed over. Character references are decoded, white space in a block becomes
one space, and blocks are joined in page order by one line break; nothing else is dropped or cut.

A page is read in one pass: an end of a tag or comment that is missing is looked for once, elements to close are counted,
and containers deeper than ``DEEPEST`` belong to the one above, so odd markup costs time in proportion to its length.

Null and empty html give an empty text; a null or odd url is a host of its own kind (empty name). Repeated rows are read
one by one; an empty table gives an empty result. Columns other than page_id, url and html are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from html import unescape

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import store, table

# HTML element names by role, and name parts of page furniture.
BLOCKS = set("address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead tr ul".split())
CONTAINERS = set("html body article main section div td".split())
FURNITURE = set("nav header footer aside menu dialog button select label fieldset input".split())
RAW = set("script style noscript template svg iframe textarea object canvas video audio title".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
HEADINGS = set("h1 h2 h3 h4 h5 h6".split())
ROLES = set("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar".split())
READERS = re.compile(r"(?:^|[-_\s])(?:comments?|commentlist|respond|reply|replies|disqus|discussion)(?:$|[-_\s\d])", re.I)
NAMES = re.compile(
    r"(?:^|[-_\s])(?:ads?|advert\w*|adslot|adbox|sponsor\w*|promo\w*|banner|cookies?\w*|consent|gdpr|notices?|notification|alert|sidebars?|side|nav\w*|menus?|breadcrumbs?|header|masthead|topbar|footer|copyright|comments?|commentlist|respond|reply|replies|disqus|discussion|share|sharing|social|related|recommend\w*|newsletter|subscribe|signup|login|search\w*|popup|modal|overlay|widgets?|pager|pagination|toolbar|skip\w*)(?:$|[-_\s\d])",
    re.I,
)
#: What follows the name of a tag up to its end; quoted values may hold the end sign. Possessive, so a failure costs one pass.
REST = re.compile(r"[^>\"']*+(?:\"[^\"]*+\"[^>\"']*+|'[^']*+'[^>\"']*+)*+>")
NAME = re.compile(r"(/?)([a-zA-Z][^\s/>]{0,63})")
ATTRIBUTE = re.compile(r"([a-zA-Z-]++)\s*+(?:=\s*+(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
#: An opening element ends an open one of these, up to the named borders.
ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dd": ({"dd", "dt"}, {"dl"}), "dt": ({"dd", "dt"}, {"dl"}), "tr": ({"tr"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
WINNERS, DEEPEST = 3, 256
#: Kinds of marked elements: never text; furniture by tag or role; by name, or a form; by name, written by readers; an article's own header.
GONE, TAGGED, NAMED, READ, OWN = range(5)


def _attributes(text: str) -> dict[str, str]:
    return {m[1].lower(): m[2] or m[3] or m[4] or "" for m in ATTRIBUTE.finditer(text)}


def _kind(tag: str, attrs: dict[str, str], inside: bool) -> int | None:
    """How an element is marked as furniture, if it is; ``inside``: of an article or main part."""
    if tag == "head" or attrs and ("hidden" in attrs or attrs.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", attrs.get("style", ""), re.I)):
        return GONE
    if tag == "header" and inside:
        return OWN
    if tag in FURNITURE or attrs and attrs.get("role", "").lower() in ROLES:
        return TAGGED
    if tag == "form":
        return NAMED
    if not attrs or tag in ("body", "html", "article", "main"):
        return None
    names = f"{attrs.get('class', '')} {attrs.get('id', '')}"
    if tag not in BLOCKS:
        # words in a sentence: only a name that is furniture as a whole counts
        return NAMED if any(NAMES.fullmatch(x) for x in names.split()) else None
    return READ if READERS.search(names) else NAMED if NAMES.search(names) else None


def tags(html: str):
    """(text before, closing, name, attributes) of each tag in page order, and the text after the last one with name None; comments and declarations have an empty name."""
    at, size, quotes, last = 0, len(html), True, html.rfind(">")
    comment_end = html.rfind("-->")
    begin = 0
    while True:
        at = html.find("<", at)
        if at < 0 or at > last:
            # nothing that is open from here on ends; an open comment hides the rest
            hide = html.find("<!--", begin) if at >= 0 else -1
            yield html[begin : hide if hide >= 0 else size], False, None, ""
            return
        after = html[at + 1 : at + 2]
        if after in ("!", "?"):
            if html.startswith("<!--", at):
                if at > comment_end:
                    yield html[begin:at], False, None, ""
                    return
                end = html.find("-->", at + 2) + 3
            else:
                end = html.find(">", at) + 1
            yield html[begin:at], False, "", ""
            begin = at = end
            continue
        name = NAME.match(html, at + 1)
        if not name:
            at += 1
            continue
        rest = REST.match(html, name.end()) if quotes else None
        if rest is None:
            # a quote without an end: from here on quotes are signs like others, which costs one search and not one for each tag
            quotes = False
            end = html.find(">", name.end()) + 1
        else:
            end = rest.end()
        yield html[begin:at], bool(name[1]), name[2].lower(), html[name.end() : end - 1]
        begin = at = end
        if not name[1] and name[2].lower() in RAW and not html[:end].endswith("/>", end - 2):
            # what stands in it is no markup
            close = re.compile(f"</{name[2]}", re.I).search(html, end)
            stop = html.find(">", close.end()) if close else -1
            if stop < 0:
                return
            begin = at = stop + 1


class Page:
    """Blocks (text, characters in links, container, mark), containers (path, parent) and marked elements (kind, parent) of one page."""

    def __init__(self, html: str):
        self.blocks: list[tuple[str, int, int, int]] = []
        self.paths, self.parents, self.names, self.depth = ["html"], [-1], ["html"], [0]
        self.marks: list[tuple[int, int, int]] = []  # kind, mark around it, container around it
        self.headed: set[int] = set()  # marks that hold a heading, and those that hold the first one of the page
        self.top: set[int] = set()
        stack: list[tuple[str, int, int, bool]] = []  # name; container and mark before it; whether it is furniture within a block
        open_: Counter = Counter()
        inline: list[Counter] = [Counter()]  # inline elements that are open within each open block
        buffer: list[str] = []
        linked = links = here = articles = skip = 0
        mark = -1

        def flush():
            nonlocal linked
            if buffer:
                if text := " ".join("".join(buffer).split()):
                    self.blocks.append((text, linked, here, mark))
                buffer.clear()
            linked = 0

        def pop():
            nonlocal here, mark, links, articles, skip
            name, container, marked, skipped = stack.pop()
            open_[name] -= 1
            skip -= skipped
            if name in BLOCKS:
                flush()
                inline.pop()
            else:
                inline[-1][name] -= 1
            links -= name == "a"
            articles -= name in ("article", "main")
            here, mark = container, marked

        for before, closing, tag, rest in tags(html):
            if before and not skip and (mark < 0 or self.marks[mark][0] != GONE):
                piece = unescape(before) if "&" in before else before
                buffer.append(piece)
                if links:
                    linked += len(piece)
            if tag is None:
                break
            if not tag:
                continue
            if closing:
                if tag == "br" or tag == "p" and not open_["p"]:
                    buffer.append(" ")
                elif open_[tag] and (tag in BLOCKS or inline[-1][tag]):
                    while stack[-1][0] != tag:
                        pop()
                    pop()
                continue
            if tag in VOID:
                if tag == "hr":
                    flush()
                elif tag == "br":
                    buffer.append(" ")
                continue
            if tag in RAW:
                continue
            if tag in BLOCKS:
                flush()
                ended, border = ENDS.get(tag, ({"p"}, {"td", "th", "button", "table"}))
                if any(open_[x] for x in ended):
                    for k in range(len(stack) - 1, -1, -1):
                        if stack[k][0] in ended:
                            while len(stack) > k:
                                pop()
                            break
                        if stack[k][0] in border or stack[k][0] in CONTAINERS and tag != "tr":
                            break
            attrs = _attributes(rest) if rest and not rest.isspace() else {}
            kind = _kind(tag, attrs, articles > 0)
            within = kind is not None and tag not in BLOCKS
            skip += within
            stack.append((tag, here, mark, within))
            open_[tag] += 1
            if tag in BLOCKS:
                inline.append(Counter())
            else:
                inline[-1][tag] += 1
            links += tag == "a"
            articles += tag in ("article", "main")
            if kind is not None and not within and (mark < 0 or self.marks[mark][0] != GONE):
                self.marks.append((kind, mark, here))
                mark = len(self.marks) - 1
            if tag in HEADINGS:
                first, k = not self.headed and not self.top, mark
                if tag == "h1" or first:
                    while k >= 0:
                        self.headed.add(k)
                        if tag == "h1":
                            self.top.add(k)
                        k = self.marks[k][1]
                elif mark >= 0:
                    self.headed.add(mark)
            if tag in CONTAINERS and tag != "html" and self.depth[here] < DEEPEST:
                classes = sorted(re.sub(r"\d+", "#", c) for c in attrs.get("class", "").lower().split())
                name = ".".join([tag, *classes])
                self.paths.append(f"{self.paths[here]}>{name}")
                self.parents.append(here)
                self.names.append(name)
                self.depth.append(self.depth[here] + 1)
                here = len(self.paths) - 1
        while stack:
            pop()
        flush()
        self._settle()

    def _settle(self) -> None:
        """Drop the blocks of furniture, once it is known how much of the page each marked element holds."""
        if not self.marks:
            self.blocks = [(t, linked, c) for t, linked, c, _ in self.blocks]
            return
        weight, every = [0.0] * len(self.marks), 0.0
        for text, linked, _, m in self.blocks:
            w = _worth(text, linked)
            every += w
            if m >= 0:
                weight[m] += w
        for m in range(len(self.marks) - 1, -1, -1):  # an element stands before those in it
            if self.marks[m][1] >= 0:
                weight[self.marks[m][1]] += weight[m]

        def off(m: int, names: bool) -> bool:
            kind = self.marks[m][0]
            if kind == OWN:
                return m not in self.headed
            if kind == NAMED:
                return names and m not in self.top and 2 * weight[m] <= every
            return kind in (GONE, TAGGED) or names

        for names in (True, False):
            dropped = [False] * len(self.marks)
            for m, (_, around, _) in enumerate(self.marks):
                dropped[m] = off(m, names) or around >= 0 and dropped[around]
            left = [(t, linked, c) for t, linked, c, m in self.blocks if m < 0 or not dropped[m]]
            if left:
                break
        self.blocks = left

    def scores(self) -> tuple[list[float], list[bool]]:
        """Of each container with all that it holds: the score of its text, and whether running text is among it."""
        score, running = [0.0] * len(self.paths), [False] * len(self.paths)
        for text, linked, c in self.blocks:
            score[c] += _worth(text, linked)
            running[c] |= len(text) > 80 and 2 * linked < len(text)
        for c in range(len(self.paths) - 1, 0, -1):  # a parent stands before its children
            score[self.parents[c]] += score[c]
            running[self.parents[c]] |= running[c]
        return score, running

    def best(self) -> tuple[int, float]:
        """The smallest container with all running text, and its share of the page's score; (-1, 0) without text.

        Without running text it is the smallest with nine tenths of the score. What stands beside an article or main part
        counts only if it is such a part too or holds half of that part's score."""
        if not self.blocks:
            return -1, 0.0
        score, running = self.scores()
        if score[0] <= 0:
            return 0, 0.0
        children: list[list[int]] = [[] for _ in self.paths]
        for c, parent in enumerate(self.parents):
            if parent >= 0:
                children[parent].append(c)
        direct = [False] * len(self.paths)
        for text, linked, c in self.blocks:
            direct[c] |= len(text) > 80 and 2 * linked < len(text)
        marked = lambda c: self.names[c].partition(".")[0] in ("article", "main")
        at = 0
        while children[at]:
            k = max(children[at], key=lambda c: (score[c], -c))
            beside = [c for c in children[at] if c != k and running[c]]
            if marked(k):
                stay = score[at] > 1.5 * score[k] or any(marked(c) for c in beside)
            elif running[at]:
                stay = direct[at] or bool(beside) or not running[k]
            else:
                stay = score[k] < 0.9 * score[at]
            if stay:
                break
            at = k
        return at, score[at] / score[0]

    def text(self, containers: list[int]) -> str:
        """Text of all ``containers`` in page order."""
        inside = [False] * len(self.paths)
        for c in containers:
            inside[c] = True
        for c, parent in enumerate(self.parents):
            if parent >= 0 and inside[parent]:
                inside[c] = True
        return "\n".join(t for t, _, c in self.blocks if inside[c])

    def extract(self, winners: list[str]) -> str:
        """Text of all containers of the first winner that holds any.

        Where the page's own best container surrounds them and holds running text that they leave out, the page is cut
        otherwise than its host's others, and its own container is taken."""
        best, _ = self.best()
        if best < 0:
            return ""
        score, _ = self.scores()
        around = set()
        for path in winners:
            mine = [c for c, p in enumerate(self.paths) if p == path]
            found = self.text(mine)
            if not found:
                continue
            around = set()
            for c in mine:
                up = self.parents[c]
                while up >= 0 and up != best:
                    up = self.parents[up]
                around.add(up == best)
            outer = [c for c in mine if not any(self._within(c, o) for o in mine if o != c)]
            if around == {True} and sum(score[c] for c in outer) < 0.9 * score[best]:
                return self.text([best])
            return found
        return self.text([best])

    def _within(self, c: int, outer: int) -> bool:
        while c > outer:
            c = self.parents[c]
        return c == outer


def _worth(text: str, linked: int) -> float:
    prose = max(0.0, 1 - linked / max(len(text), 1))
    return prose * (min(len(text) / 100, 30) + text.count(",") + (len(text) > 80))


def host_of(url):
    return F.coalesce(F.regexp_extract(F.lower(url), r"^[a-z][a-z0-9+.-]*://(?:[^/@]*@)?([^/:?#]+)", 1), F.lit(""))


def host_paths(pages: DataFrame, winners: int = WINNERS) -> DataFrame:
    """host and its ``paths`` with most votes, best first."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            rows: list[list] = [[], [], []]
            for host, html in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                page = Page(html or "")
                k, share = page.best()
                if k >= 0:
                    for c, v in zip(rows, (host, page.paths[k], share)):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([pa.array(rows[0], pa.string()), pa.array(rows[1], pa.string()), pa.array(rows[2], pa.float64())], names=["host", "path", "share"])

    votes = pages.select(host_of(F.col("url")).alias("host"), "html").mapInArrow(run, "host string, path string, share double")
    summed = votes.groupBy("host", "path").agg(F.round(F.sum("share"), 6).alias("votes"))
    ranked = summed.withColumn("r", F.row_number().over(Window.partitionBy("host").orderBy(F.desc("votes"), "path"))).filter(F.col("r") <= winners)
    return ranked.groupBy("host").agg(F.transform(F.sort_array(F.collect_list(F.struct("r", "path"))), lambda x: x["path"]).alias("paths"))


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text for each row of ``pages`` (page_id, url, html)."""
    # stored, so that Spark knows its size when it chooses how to join
    winners = store(host_paths(pages), "host-paths")

    def run(batches):
        import pyarrow as pa

        for b in batches:
            text = [Page(html or "").extract(paths or []) for html, paths in zip(b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(text, pa.string())], names=["page_id", "url", "text"])

    joined = pages.select("page_id", "url", "html", host_of(F.col("url")).alias("host")).join(winners, "host", "left")
    kinds = dict(pages.dtypes)
    return joined.select("page_id", "url", "html", "paths").mapInArrow(run, f"page_id {kinds['page_id']}, url string, text string")


def query(spark, sf_dir):
    out = main_text(table(spark, sf_dir, "pages", "page_id", "url", "html"))
    return out.withColumn("n_chars", F.char_length("text").cast("long"))
