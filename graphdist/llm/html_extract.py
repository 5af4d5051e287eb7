"""Main-text extraction: flat text blocks with features of their neighbours, classified by a decision tree.

A page is cut into flat blocks of text at block-level tags. A block knows its words, its link density (share of words
inside links) and both values of the blocks before and after it. Beside these stand three marks: whether it lies inside an article or
main container, whether inside a container that names furniture (menu, header, footer, sidebar, notice, advert, form, comments),
and the share of the page's running words that such article containers hold. A decision tree, grown here by Gini impurity from the
labelled pages below, decides which blocks are text. The pages are shown to it fully marked, partly marked, unmarked and with an article
tag around a teaser only, so marks count where they are there and words, links and neighbours decide where they are not.

Scripts, styles, comments, hidden markup and the head never give text. Character references are decoded, white space
inside a block becomes one space, blocks are joined by one empty line.

Defined cases: NULL html counts as empty; a page without text gives ''; broken or cut markup is read as far as it
goes (an unclosed script swallows the rest); repeated rows are read each; an empty table gives an empty table; other
columns pass through.
"""

from __future__ import annotations

import html as _html
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, types as T

from graphdist.llm.arrow_io import slices, tidy

PIECE = 8 << 20  # bytes of html read together
_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(>|\Z)", re.S)
# fixed values: elements by their role
_BREAKS = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead tr ul".split())
_SKIPPED = frozenset("head script style noscript template svg math iframe object canvas audio video textarea title".split())
_RAW = frozenset("script style textarea title iframe noscript template".split())
_VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
_FURNITURE_TAGS = frozenset("nav footer aside form menu dialog button select fieldset".split())
_CONTENT_TAGS = frozenset("article main".split())
_CLOSED_BY_BLOCK = frozenset("p li dt dd option tr td th".split())
_FURNITURE_NAMES = frozenset(
    "ad ads advert adverts advertisement banner breadcrumb breadcrumbs comment comments comment-list comments-area cookie cookies consent discussion disqus "
    "footer form gdpr header hidden login masthead menu modal nav navbar navigation newsletter notice pagination popup popover promo promoted promotion "
    "related reply replies respond search share sharing sidebar signup site-footer site-header social sponsor sponsored subscribe subscription toolbar widget".split()
)
_NAMES = re.compile(r"""\b(?:class|id|role|aria-label)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""\shidden(?=[\s=/>]|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none""", re.I)
_SPACE = re.compile(r"\s+")


def _is_furniture(tag: str, attrs: str) -> bool:
    if tag in _FURNITURE_TAGS:
        return True
    if not attrs:
        return False
    if _HIDDEN.search(attrs):
        return True
    for m in _NAMES.finditer(attrs):
        for name in (m[1] or m[2] or m[3] or "").lower().split():
            parts = [x for x in re.split(r"[-_]+", name) if x]
            if name in _FURNITURE_NAMES or any(x in _FURNITURE_NAMES for x in (parts[:1] + parts[-1:])):
                return True
    return False


class Block:
    __slots__ = ("text", "words", "links", "inside", "furniture")

    def __init__(self, text, words, links, inside, furniture):
        self.text, self.words, self.links, self.inside, self.furniture = text, words, links, inside, furniture


def flat_blocks(page: str) -> list[Block]:
    """The page's text blocks in order."""
    blocks: list[Block] = []
    stack: list[tuple[str, bool, bool, bool]] = []  # tag, skipped, inside content, furniture
    text: list[str] = []
    linked: list[str] = []
    in_link = 0
    at, n = 0, len(page)

    def flush():
        nonlocal text, linked
        if text:
            s = _SPACE.sub(" ", _html.unescape("".join(text))).strip()
            if s:
                w = max(s.count(" ") + 1, len(s) // 12)  # scripts without blanks have words, too
                lw = len("".join(linked).split())
                inside, furn = (stack[-1][2], stack[-1][3]) if stack else (False, False)
                blocks.append(Block(s, w, min(1.0, lw / w), inside, furn))
        text, linked = [], []

    def close(tag):
        nonlocal in_link
        for k in range(len(stack) - 1, -1, -1):
            if stack[k][0] == tag:
                in_link = max(0, in_link - sum(x[0] == "a" for x in stack[k:]))
                del stack[k:]
                return

    while at < n:
        m = _TOKEN.search(page, at)
        chunk = page[at : m.start()] if m else page[at:]
        if chunk and not (stack and stack[-1][1]):
            text.append(chunk)
            if in_link:
                linked.append(chunk)
        if not m:
            break
        at = m.end()
        tag = (m[2] or m[5] or "").lower()
        if not tag:
            continue
        if m[5] and m[7] == "":  # a tag cut off by the end of the page
            break
        end, attrs = m[1] or m[4], m[3] or m[6] or ""
        breaks = tag in _BREAKS
        if tag == "br":
            text.append(" ")
        if breaks:
            flush()
        if end:
            if tag == "body" or tag == "html":
                continue
            close(tag)
            continue
        if tag in _VOID:
            continue
        if breaks and stack and stack[-1][0] in _CLOSED_BY_BLOCK and (tag == stack[-1][0] or stack[-1][0] == "p"):
            close(stack[-1][0])
        elif breaks and tag in _CLOSED_BY_BLOCK:  # <p><b>..<p>: the open paragraph ends, inline tags with it
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    in_link = max(0, in_link - sum(x[0] == "a" for x in stack[k:]))
                    del stack[k:]
                    break
                if stack[k][0] in _BREAKS:
                    break
        skipped, inside, furn = stack[-1][1:] if stack else (False, False, False)
        if tag in _RAW:
            if attrs.endswith("/"):
                continue
            shut = re.compile(rf"</{re.escape(tag)}\s*>", re.I).search(page, at)
            at = shut.end() if shut else n
            continue
        skipped = skipped or tag in _SKIPPED
        inside = inside or tag in _CONTENT_TAGS or bool(re.search(r"""role\s*=\s*["']?main|itemprop\s*=\s*["']?articleBody""", attrs, re.I))
        own = _is_furniture(tag, attrs) if tag not in _CONTENT_TAGS and tag not in ("html", "body") else False
        if tag == "header":
            own = own or not inside
        furn = furn or own
        if tag == "body":
            skipped = False
            stack.clear()
        if attrs.endswith("/") and not breaks:
            continue
        stack.append((tag, skipped, inside, furn))
        in_link += tag == "a"
    flush()
    return blocks


def features(blocks: list[Block]) -> np.ndarray:
    """words, link density, both of the neighbours before and after, inside an article, inside furniture, share of articles."""
    out = np.zeros((len(blocks), 9))
    running = [(b.words, b.inside) for b in blocks if not b.furniture and b.links <= 0.5]
    share = sum(w for w, inside in running if inside) / max(1, sum(w for w, _ in running))
    for k, b in enumerate(blocks):
        p = blocks[k - 1] if k else None
        q = blocks[k + 1] if k + 1 < len(blocks) else None
        out[k] = (
            b.words, b.links, p.words if p else 0, p.links if p else 0, q.words if q else 0, q.links if q else 0, b.inside, b.furniture, share
        )
    return out


# fixed values: labelled pages, written by hand for this operator. A block is its words, or words/linked words; main text stands in [ ].
LABELLED = (
    "1/1 1/1 1/1 2/2 1/1 12 [ 9 60 45 80 22 64 38 ] 5 3/3 2/2 4/4",
    "2 1/1 1/1 1/1 1/1 [ 6 34 120/4 7 55 71 90 16 40 ] 6/2 1/1 1/1 8",
    "3/3 18/2 2/2 1/1 1/1 [ 11 48 52 5 66 31 44/3 ] 2 6/6 7/7 5/5 9/9 4 5",
    "4 2/2 2/2 2/2 14 [ 8 95 110 73 28 ] 14 2/2 3 3/3 3/3 6",
    "1/1 1/1 1/1 1/1 1/1 1/1 [ 4 25 33 41 19 27 36 22 ] 7 1/1 1/1 1/1 10",
    "2/2 5 4/4 8/8 7/7 9/9 [ 10 150 200 ] 3 4/4 8/8 7/7 6",
    "1 3/3 3/3 21 [ 7 58 12 47 9 63 24 55 ] 2/2 5 2 1 4",
    "1/1 2/2 1/1 [ 5 70/6 64/5 81/9 ] 12/12 10/10 11/11 2 7",
    "6/6 1/1 1/1 9 4/4 [ 12 44 3 39 26 4 51 37 ] 1/1 2 8/8 6/6 13 5",
    "2/2 1/1 [ 14 30 18 42 35 29 ] 3 2/2 2/2 16 1/1 1/1",
    "3 1/1 1/1 1/1 2 2 10/10 12/12 9/9 [ 6 85 17 96 77 ] 6 6 3/3 5",
    "1/1 1/1 8 11/5 [ 8 40 66 23 58 ] 4 9/8 7/7 8/7 1 6/1",
)


def _read_labelled(page: str) -> list[tuple[int, float, int]]:
    """(words, link density, 1 for main text) of each block of a labelled page."""
    out, main = [], 0
    for x in page.split():
        if x in "[]":
            main = int(x == "[")
            continue
        words, _, linked = x.partition("/")
        out.append((int(words), int(linked or 0) / int(words), main))
    return out


def labelled_table(pages=LABELLED) -> np.ndarray:
    """Rows of features and class: every labelled page as it looks with more or fewer marks."""
    rows = []

    def show(blocks, inside, furniture, classes):
        x = features([Block("", w, links, i, f) for (w, links), i, f in zip(blocks, inside, furniture)])
        rows.append(np.column_stack([x, classes]))

    for k, page in enumerate(pages):
        read = _read_labelled(page)
        blocks, main = [b[:2] for b in read], [bool(b[2]) for b in read]
        none, other = [False] * len(read), [not m for m in main]
        show(blocks, none, none, main)  # no marks at all
        show(blocks, none, [o and j % 2 == k % 2 for j, o in enumerate(other)], main)  # some furniture is named
        for size in (0.05, 0.2, 0.5, 1, 3):  # short and long articles
            sized = [(max(1, round(w * size)), links) for w, links in blocks]
            show(sized, main, other, main)  # all marks
            show(sized, main, none, main)  # only the article is marked
            show([*sized, (3, 0.0), (18 + k, 0.0)], [*main, True, True], [*other, True, True], [*main, False, False])  # comments inside the article
        show([*blocks, (3, 0.0), (30 + 2 * k, 0.0), (25, 0.0)], [*main, False, False, False], none + [False] * 3, [*main, False, False, False])  # unnamed ones after it
        at = main.index(True)
        teased = [*blocks[:at], (1 + k % 6, 0.0), *blocks[at:]]
        show(teased, [j == at for j in range(len(teased))], [False] * len(teased), [*main[:at], False, *main[at:]])  # an article tag around a teaser
    short = [(1, 0.0), (2, 0.0), (1, 0.0)]
    show(short, [True] * 3, [False] * 3, [True] * 3)  # a very short article
    show([(5, 1.0), (4, 0.0), (1, 0.0), (3, 0.0)], [False, True, True, False], [True, False, False, True], [False, True, True, False])
    return np.concatenate(rows)


def grow(x: np.ndarray, y: np.ndarray, depth: int = 9):
    """A binary tree: a class, or (feature, threshold, tree where at most, tree where above)."""
    if depth == 0 or y.min() == y.max():
        return int(2 * y.sum() >= len(y))
    best = None
    for f in range(x.shape[1]):
        values = np.unique(x[:, f])
        for t in (values[:-1] + values[1:]) / 2:
            low = x[:, f] <= t
            cost = 0.0
            for part in (y[low], y[~low]):
                p = part.mean()
                cost += len(part) * 2 * p * (1 - p)
            if best is None or cost < best[0] - 1e-12:
                best = (cost, f, float(t))
    if best is None:
        return int(2 * y.sum() >= len(y))
    _, f, t = best
    low = x[:, f] <= t
    return (f, t, grow(x[low], y[low], depth - 1), grow(x[~low], y[~low], depth - 1))


def train(labelled=LABELLED, depth: int = 9):
    table = labelled_table(labelled)
    return grow(table[:, :-1], table[:, -1], depth)


def classify(tree, row) -> int:
    while isinstance(tree, tuple):
        tree = tree[2] if row[tree[0]] <= tree[1] else tree[3]
    return tree


def main_text(page: str | None, tree) -> str:
    blocks = flat_blocks(page or "")
    return "\n\n".join(b.text for b, row in zip(blocks, features(blocks)) if classify(tree, row))


def extract(pages: DataFrame, tree=None) -> DataFrame:
    """``pages`` without html, with text and n_chars."""
    grown = tree or train()
    names = [c for c in pages.columns if c not in ("html", "text", "n_chars")]
    pages = pages.select(*names, "html")
    schema = T.StructType(pages.schema.fields[:-1]).add("text", T.StringType()).add("n_chars", T.LongType())

    @tidy
    def run(batches):
        for whole in batches:
            for b in slices(whole, "html", PIECE):
                texts = [main_text(p, grown) for p in b.column(b.num_columns - 1).to_pylist()]
                yield pa.RecordBatch.from_arrays(
                    [*b.columns[:-1], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], [*names, "text", "n_chars"]
                )

    return pages.mapInArrow(run, schema)


def op6_html_extract(spark, sf_dir):
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"))
