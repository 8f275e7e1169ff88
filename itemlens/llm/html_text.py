"""Main text of web pages from flat text blocks, classified by a small decision tree.

A page is read once as a stream of tags and texts and becomes a list of blocks.  Each block has
its word count and link density, those of its neighbours, and what encloses it: elements that are
beside the text by their meaning, an article, and how strongly class names speak against it.  A
tree that is grown from the blocks of the labelled pages below tells main text from the rest; class
names that only partly or weakly speak against a block are outweighed by its words and links.
"""

from __future__ import annotations

import html
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Names of HTML elements.
_SILENT = frozenset("script style noscript template textarea select svg math iframe object canvas head title button video audio datalist".split())
_INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd mark q s samp small span strike strong sub sup time tt u var wbr".split())
_BOX = frozenset("html body div section article main nav aside footer header form ul ol dl table tbody thead tfoot tr td th figure fieldset details dialog menu blockquote".split())
_AROUND = frozenset("nav aside footer form menu dialog fieldset".split())
_CENTRE = frozenset("article main".split())
# Words of class names that say what a box is: always, or only if the name has no other word that counts.
_STRONG = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo promotion sidebar menu nav navbar navigation footer cookie cookies consent gdpr notice notices alert banner popup modal overlay "
    "newsletter subscribe signup related recommended recommendations comment comments commentlist respond reply replies discussion disqus breadcrumb breadcrumbs pagination pager toolbar masthead topbar taboola outbrain paywall".split()
)
_WEAK = frozenset("share sharing social widget login search copyright legal disclaimer skip tags".split())
_NEUTRAL = frozenset("box block wrap wrapper container list item items area section unit slot left right bottom inner outer col row main page site js is has link links text body title bar button buttons form".split())
_TOP_HINTS = frozenset("header head top".split())
#: Elements that hold text alone: only their own closing tag ends them.
_RAW = {n: re.compile(rf"</{n}(?=[\s/>])", re.I) for n in ("script", "style", "textarea", "title")}
_CENTRE_HINTS = frozenset("article post entry story content main".split())

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|[^<]+|<", re.S)
_CLASS = re.compile(r"""(?:^|\s)(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s>]+))""", re.I)
_SPLIT = re.compile(r"[^a-z0-9]+")

FEATURES = ("words", "link_density", "words_before", "link_density_before", "words_after", "link_density_after", "around", "centre", "page_has_centre", "heading", "against")

#: Where a block of a labelled page stands: around, centre, heading, and how strongly class names speak against it.
_PLACES = {
    "n": (1, 0, 0, 0.0), "an": (1, 1, 0, 0.0), "a": (0, 1, 0, 0.0), "ah": (0, 1, 1, 0.0), "b": (0, 0, 0, 0.0), "bh": (0, 0, 1, 0.0), "s": (0, 0, 0, 1.0), "as": (0, 1, 0, 1.0),
    "w": (0, 0, 0, 0.8), "aw": (0, 1, 0, 0.8), "m": (0, 0, 0, 0.4), "am": (0, 1, 0, 0.4),
}
#: Labelled pages: of each block in order its place, its words, after a slash those in links, and "!" if it is main text.
LABELLED = (
    # articles with menus, adverts, notices, comments and footers, inside the article or not
    "n1/1 n1/1 n2/2 s12 ah8! a60! a45! a3! a20! a55! n9",
    "n1/1 n3/3 ah6! a30! a12/4! a90! as35 a50! as20/10 a7! a25! n5 n12/3",
    "b12 n2/2 ah9! a25! a4/4! a40! as3 as60 as45 n70 b40 b8/8 n7",
    "b3/3 b2/2 b90 a200! a15! a1! a2! a100! b60 b25/20 s40",
    "n4/4 a12! a6! ah3! a5! a16! ah2! a1/1! a30! an35 an5/5 a70! n20/10 n3",
    "s60 n1/1 a90/5! b5 b150 s120 s80 b30/6",
    "n2/2 ah7! a50! a2/2 a3/3 a2/2 a1/1 a4/4 a3/3 a60! a35! n8",
    "a80! a5/5 a6/6 a4/4 a8/8 a5/5 b20 b3/3",
    "n1/1 a20! a2/2! a35! a4/4! a18! b14 b45/5",
    "n2/2 ah2! a2! a3/1! as30 a5/2! a4/1! a2! a6/3! a9/4! a8! n4",
    "ah6! a3! a4/4! a5! a2! a3/3! a4! a1! a6! a2/2! a3! a4/4 a5/5 a3/3 a6/6 a40!",
    "a4! a3/3 a4/4 a2/2 a3/3 a5! a6/6! a4! a7! a2/2 a2/2 a3/3 a4/4 as6 a3/1!",
    # class names that speak weakly, or only in part
    "n2/2 a40! am60! am12! a30! am3/3 am2/2 a50! am25/3! aw4/4 aw6 aw3/3 a45! n6",
    "a50! am30! am2/2 a40! am4/4 a45! am3/3 am28! am1/1 a60! am5/4 a9! am2/2 a30!",
    "n1/1 am90! am45! am10! am4/4 am6/5 aw8 aw12/8 aw70! a30! aw5 n9",
    "b2/2 m60! m35! m5/5 b50! m2 w4/4 w5 w9/7 b40! w60! m20! m8/8 b3/3",
    # pages without an article
    "b1/1 b1/1 b2/2 b3/3 bh7! b50! b45! b6! b60! b18! b4/4 b5/5",
    "n3/3 n2/2 bh5! b25! b30! b3! b20! b14! b16! b15/1! b40! n9 s12",
    "b4/4 b2 b3/3 bh3 b1/1 b35/2! b90! b13! b15! b7/7 b8/8 b7/7 b2 b3/3",
    "b150! b8! b12/10 b30/21 b30/21 b30/21 n40",
    "s70 b16! b14! b60! s35 s8 b25/22 b12/9 b4/4",
    "b60! n45 n2/2 b90!",
    "b3/3 b2 b2/2 b4/4 b1 b3/3",
)


def labelled_rows() -> np.ndarray:
    """The blocks of the labelled pages: their FEATURES, then 1 for main text."""
    out = []
    for page in LABELLED:
        found = []
        for place, words, linked, main in re.findall(r"([a-z]+)([0-9]+)(?:/([0-9]+))?(!?)", page):
            around, centre, heading, against = _PLACES[place]
            found.append((["", int(words), int(linked or 0), around, centre, heading, against], main == "!"))
        out += [(*row, main) for row, (_, main) in zip(block_features([b for b, _ in found]), found, strict=True)]
    return np.array(out, float)


def grow(rows: np.ndarray, labels: np.ndarray, depth: int = 12) -> tuple | int:
    """A decision tree by Gini impurity: (feature, threshold, tree if at most, tree if above) or a label."""
    share = labels.mean()
    if not depth or share in (0.0, 1.0):
        return int(share >= 0.5)
    best = None
    for f in range(rows.shape[1]):
        values = np.unique(rows[:, f])
        for t in (values[:-1] + values[1:]) / 2:
            low = rows[:, f] <= t
            cost = sum(len(y) * y.mean() * (1 - y.mean()) for y in (labels[low], labels[~low]))
            if best is None or cost < best[0] - 1e-12:
                best = (cost, f, float(t), low)
    if best is None:
        return int(share >= 0.5)
    _, f, t, low = best
    return (f, t, grow(rows[low], labels[low], depth - 1), grow(rows[~low], labels[~low], depth - 1))


def default_tree() -> tuple | int:
    table = labelled_rows()
    return grow(table[:, :-1], table[:, -1])


def decide(tree: tuple | int, row: tuple) -> int:
    while isinstance(tree, tuple):
        tree = tree[2] if row[tree[0]] <= tree[1] else tree[3]
    return tree


def against_of(names: list[str]) -> float:
    """How strongly class names speak against a box: 1 by a strong word, 0.8 by weak words alone, 0.4 by weak words among others."""
    found = 0.0
    for name in names:
        pieces = {p for p in _SPLIT.split(name) if p and not p.isdigit()} - _NEUTRAL
        if pieces & _STRONG:
            return 1.0
        if weak := pieces & _WEAK:
            found = max(found, 0.8 if len(weak) == len(pieces) else 0.4)
    return found


def blocks(page: str) -> list[list]:
    """[text, words, words in links, around, centre, heading, against] of each text block in page order."""
    out: list[list] = []
    stack: list[tuple[str, bool, bool, float]] = []  # open boxes: name, around, centre, against
    around = centre = False
    against = 0.0
    silent, link, heading = None, False, False
    depth = 0
    buffer: list[str] = []
    linked: list[str] = []

    def flush() -> None:
        if buffer:
            text = " ".join("".join(buffer).split())
            if text:
                out.append([text, text.count(" ") + 1, min(text.count(" ") + 1, len(" ".join(linked).split())), around, centre, heading, against])
            buffer.clear()
            linked.clear()

    tokens = _TOKEN.finditer(page)
    while (m := next(tokens, None)) is not None:
        name = m.group(2)
        if name is None:
            piece = m.group(0)
            if silent is None and (piece[0] != "<" or piece == "<"):
                piece = html.unescape(piece) if "&" in piece else piece
                buffer.append(piece)
                if link:
                    linked.append(piece)
            continue
        name, closing = name.lower(), m.group(1)
        if name in _RAW and not closing and not m.group(3).endswith("/"):
            end = _RAW[name].search(page, m.end())
            if end is None:
                break
            tokens = _TOKEN.finditer(page, end.start())
            continue
        if silent is not None:
            if name == silent:
                depth += -1 if closing else 1
                if depth <= 0:
                    silent = None
            elif name == "body" and silent == "head":
                silent = None
            continue
        if name in _SILENT:
            if not closing and not m.group(3).endswith("/"):
                silent, depth = name, 1
                if name == "head":
                    flush()
            continue
        if name in _INLINE:
            if name == "a":
                link = not closing
            continue
        flush()
        if name in _BOX:
            link = False
            if closing:
                for i in range(len(stack) - 1, -1, -1):
                    if stack[i][0] == name:
                        del stack[i:]
                        break
                _, around, centre, against = stack[-1] if stack else ("", False, False, 0.0)
            elif not m.group(3).endswith("/"):
                names = [n for c in _CLASS.finditer(m.group(3)) for n in (c.group(1) or c.group(2) or c.group(3) or "").lower().split()]
                marks = {p for n in names for p in _SPLIT.split(n)}
                plain = name in ("html", "body", "article", "main")
                inner = centre or name in _CENTRE or bool(marks & _CENTRE_HINTS and name in ("div", "section"))
                outer = around or name in _AROUND
                outer = outer or not centre and (name == "header" or bool(marks & _TOP_HINTS) and name in ("div", "section", "ul", "table"))
                # An article within a box that is only weakly marked speaks for itself.
                weight = (against if against == 1 or name not in _CENTRE else 0.0) if plain else max(against, against_of(names))
                stack.append((name, outer, inner, weight))
                around, centre, against = outer, inner, weight
        elif name[0] == "h" and name[1:].isdigit():
            heading = not closing
    flush()
    return out


def block_features(found: list[list]) -> list[tuple]:
    """The FEATURES of each of a page's blocks; beyond its ends are blocks without words."""
    has_centre = any(b[4] and not b[3] and b[6] < 1 for b in found)
    ends = [["", 0, 0], *found, ["", 0, 0]]
    density = [b[2] / b[1] if b[1] else 0.0 for b in ends]
    return [
        (n, density[i], ends[i - 1][1], density[i - 1], ends[i + 1][1], density[i + 1], around, centre, has_centre, heading, against)
        for i, (_, n, _, around, centre, heading, against) in enumerate(found, 1)
    ]


def main_text(page: str | None, tree: tuple | int) -> str:
    if not page:
        return ""
    found = blocks(page)
    return " ".join(b[0] for b, row in zip(found, block_features(found), strict=True) if decide(tree, row))


def extracted(pages: DataFrame, tree: tuple | int | None = None) -> DataFrame:
    """One row per row of pages (page_id, url, html): page_id, url, text, n_chars of the main text.

    Null and empty pages, and pages without main text, have the empty text.  Character references
    are decoded, white space within a block becomes one space, and blocks are joined by one.  Pages
    are read whole; broken markup is read as far as it goes.  An empty table gives no rows.
    """
    grown = default_tree() if tree is None else tree

    def run(batches):
        for batch in batches:
            texts = [main_text(p, grown) for p in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"]
            )

    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long")
