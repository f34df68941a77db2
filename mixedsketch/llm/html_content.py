"""Main text of web pages by a maximum-scoring subsequence.

A page is a sequence of words and tags.  A word scores the log-odds, learnt on
labelled pages, that text in its place is content; a tag scores the log-odds of
its name inside against outside the content, never above zero.  One linear scan
finds the contiguous region of the highest sum.

The place of a text is told by structure alone: the element it lies in, how
much text and how many links that element and the page have, and where it
stands to the two elements an article is likely to be, the one with the most
text outside links and the one with the first headline.  Class names and ids
are not looked at.  An element inside the likely article whose own sum is
negative, such as an advert between two paragraphs, is an island: it is taken
out of the sequence before the scan.  Everything else between the two ends of
the region is main text.

Reading a page takes time in proportion to its length, however careless it is.
"""

from __future__ import annotations

import html as html_lib
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernel
from .labelled_pages import labelled_pages
from .workspace import ship

#: Elements by their part in the layout.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img svg math mrow mi mo mn ms mtext msup msub mfrac msqrt g path text tspan".split())
UNSEEN = frozenset("script style textarea title noscript template iframe select".split())
SECTIONS = frozenset("article aside body center details dialog div fieldset footer form header main nav section td th".split())
GROUPS = SECTIONS | frozenset("blockquote dl figure menu ol table ul".split())
ENDS_P = GROUPS | frozenset("address h1 h2 h3 h4 h5 h6 hr li p pre dd dt figcaption".split())
LISTS = frozenset("ul ol menu dl table".split())
TELLING_ROLES = frozenset("navigation banner contentinfo complementary search alert dialog alertdialog status main article".split())

_OPEN = re.compile(r"<(?:(/?)([a-zA-Z][^\s/>]*+)|(!--)|[!?/])")
_REST = re.compile(r"(?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+'|(?![\s\"'])))*+>")
_HINT = re.compile(r"\brole\s*=\s*[\"']?\s*([a-z]+)|(?:^|\s)(hidden)(?=[\s=/]|$)|\baria-(hidden)\s*=\s*[\"']?true", re.IGNORECASE)


@dataclass(slots=True)
class Block:
    """A run of text between block boundaries, the section it lies in, and the elements between the two."""

    text: str
    words: int
    linked: int
    section: int
    inside: tuple[str, ...]


@dataclass(slots=True)
class Section:
    """An element that may hold an article or be one of the things around it."""

    tag: str
    parent: int
    context: tuple[str, ...]
    words: int = 0
    linked: int = 0
    headline: int = -1  # token of its first h1
    blocks: int = 0
    twins: int = 1  # sections of its parent with its tag
    opens: str = ""  # element of its first block
    last: int = 0  # last section inside
    total: int = 0
    total_linked: int = 0


@dataclass
class Page:
    """Tokens in order (tag names, end tags as "/name", and Blocks), the sections, and the token ranges of group elements."""

    tokens: list
    sections: list[Section]
    groups: list[tuple[int, int, int]]  # first token, end, section around


def _tag_end(page: str, at: int, careful: bool) -> tuple[int, bool]:
    """Where the tag that is open at ``at`` ends, and whether quotes still count on this page.

    A quote that never closes is none: the tag ends at the next ">".  After
    one such tag quotes are not followed any more, which keeps reading linear.
    """
    if careful:
        m = _REST.match(page, at)
        if m:
            return m.end(), True
    end = page.find(">", at)
    return (end + 1 if end >= 0 else len(page)), False


def read(page: str) -> Page:
    """Tokens and sections of a page.

    Comments, declarations and elements that are never shown are no text; a new
    block element closes an open paragraph; an end tag without a start is
    ignored; inline elements do not end a block, but for ``ins`` between blocks.
    """
    tokens: list = []
    sections = [Section("body", -1, ())]
    groups: list[tuple[int, int, int]] = []
    # open elements: tag, section, group start or -1, place of the open p and of the open li (-1: none), tags inside the section
    stack: list[tuple[str, int, int, int, int, tuple[str, ...]]] = []
    places: dict[str, list[int]] = {}
    children: dict[tuple[int, str], int] = {}  # sections by the one around and their tag
    pieces: list[str] = []
    linked = 0  # words of the block inside links
    link = -1  # depth of the stack at which a link opened
    careful = True
    at, end = 0, len(page)

    def flush():
        nonlocal linked
        if not pieces:
            return
        words = "".join(pieces).split()
        pieces.clear()
        if words:
            section, inside = (stack[-1][1], stack[-1][5]) if stack else (0, ())
            block = Block(" ".join(words), len(words), min(linked, len(words)), section, inside)
            s = sections[section]
            s.words, s.linked, s.blocks = s.words + block.words, s.linked + block.linked, s.blocks + 1
            if s.blocks == 1:
                s.opens = inside[-1] if inside else "loose"
            if "h1" in inside and s.headline < 0:
                s.headline = len(tokens)
            tokens.append(block)
        linked = 0

    def cut(depth: int):
        """Close open elements down to ``depth``."""
        nonlocal link
        while len(stack) > depth:
            tag, section, start, *_ = stack.pop()
            places[tag].pop()
            if start >= 0:
                groups.append((start, len(tokens), section if tag not in SECTIONS else sections[section].parent))
        if link > depth:
            link = -1

    def text(piece: str):
        nonlocal linked
        if "&" in piece:
            piece = html_lib.unescape(piece)
        pieces.append(piece)
        if link >= 0:
            linked += len(piece.split())

    while at < end:
        m = _OPEN.search(page, at)
        stop = m.start() if m else end
        if stop > at:
            text(page[at:stop])
        if not m:
            break
        at = m.end()
        if m.group(3):
            at = page.find("-->", at - 2)
            if at < 0:
                break
            at += 3
            continue
        name = m.group(2)
        if page[at : at + 1] == ">":
            at += 1
        else:
            at, careful = _tag_end(page, at, careful)
        if name is None:
            continue
        tag = name.lower()
        if m.group(1):
            if tag == "a":
                link = -1
            if tag in INLINE and not places.get(tag):
                continue
            flush()
            tokens.append("/" + tag)
            if places.get(tag):
                cut(places[tag][-1])
            continue
        attrs = page[m.end() : at - 1] if at > m.end() + 1 else ""
        if tag in UNSEEN:
            if not attrs.endswith("/"):
                close = re.compile(rf"</{tag}(?=[\s/>])", re.IGNORECASE).search(page, at)
                if not close:
                    break
                at, careful = _tag_end(page, close.end(), careful)
            if tag != "noscript":
                flush()
            continue
        if tag == "xmp":
            close = re.compile(r"</xmp(?=[\s/>])", re.IGNORECASE).search(page, at)
            stop = close.start() if close else end
            flush()
            tokens.append("pre")
            pieces.append(page[at:stop])
            flush()
            at, careful = _tag_end(page, close.end(), careful) if close else (end, careful)
            continue
        between = tag == "ins" and not pieces and (not stack or stack[-1][0] in SECTIONS)
        if tag in INLINE and not between:
            if tag == "a":
                link = len(stack)
            continue
        flush()
        if tag in ENDS_P and stack and stack[-1][3] >= 0:
            cut(stack[-1][3])
        if tag == "li" and stack and stack[-1][4] >= 0:
            cut(stack[-1][4])
        tokens.append(tag)
        if tag in VOID:
            continue
        _, around, _, p, li, inside = stack[-1] if stack else ("", 0, -1, -1, -1, ())
        section = around
        if tag in ("html", "body"):
            p = li = -1
        elif tag in SECTIONS or between:
            over = sections[around]
            context = over.context if tag in over.context else (*over.context, tag)
            for hint in _HINT.finditer(attrs) if attrs else ():
                role = (hint.group(1) or "").lower()
                name = "role=" + role if role in TELLING_ROLES else "hidden" if hint.group(2) or hint.group(3) else None
                if name and name not in context:
                    context = (*context, name)
            section, inside = len(sections), ()
            sections.append(Section(tag, around, context))
            children[around, tag] = children.get((around, tag), 0) + 1
            p = li = -1
        elif tag not in inside:
            inside = (*inside, tag)
        depth = len(stack)
        start = len(tokens) - 1 if tag in GROUPS or between else -1
        stack.append((tag, section, start, depth if tag == "p" else -1 if tag in GROUPS else p, depth if tag == "li" else -1 if tag in LISTS else li, inside))
        places.setdefault(tag, []).append(depth)
    flush()
    cut(0)
    for i in range(len(sections) - 1, -1, -1):
        s = sections[i]
        s.total, s.total_linked, s.last = s.total + s.words, s.total_linked + s.linked, max(s.last, i)
        if i:
            over = sections[s.parent]
            over.total, over.total_linked, over.last = over.total + s.total, over.total_linked + s.total_linked, max(over.last, s.last)
            s.twins = children[s.parent, s.tag]
    return Page(tokens, sections, groups)


def _step(n: int) -> int:
    return min(n.bit_length(), 9)


def _share(part: int, whole: int) -> int:
    return 0 if not part else 1 + (2 * part >= whole) + (10 * part >= 9 * whole)


def _likely(page: Page) -> tuple[int, int]:
    """The sections with the most text outside links (their own and a part of their children's), and with the first headline (-1: none)."""
    mass = [float(s.words - s.linked) for s in page.sections]
    for s in page.sections[1:]:
        mass[s.parent] += 0.6 * (s.words - s.linked)
    most = max(range(len(mass)), key=lambda i: (mass[i], -i))
    heads = [(s.headline, i) for i, s in enumerate(page.sections) if s.headline >= 0]
    head = min(heads)[1] if heads else -1
    while head > 0 and page.sections[head].tag == "header":
        head = page.sections[head].parent
    return most, head


def _place(i: int, of: int, sections: list[Section]) -> str:
    if of < 0:
        return "none"
    if i == of:
        return "same"
    if of < i <= sections[of].last:
        return "in"
    if i < of <= sections[i].last:
        return "over"
    return "before" if i < of else "after"


def _known(page: Page) -> list[tuple]:
    """What is known of each section: context, tag, places, link share, sizes, sections like it, blocks, first block."""
    most, head = _likely(page)
    sections = page.sections
    whole = max(1, sections[0].total)
    first = next((i for i, s in enumerate(sections) if s.tag in ("article", "main")), -1)
    return [
        (s.context, s.tag, _place(i, most, sections), _place(i, head, sections), _place(i, first, sections), _share(s.total_linked, s.total), _step(s.total), min(9, 10 * s.total // whole), min(s.twins, 4), min(s.blocks, 4), s.opens)
        for i, s in enumerate(sections)
    ]


def section_features(known: tuple) -> list[str]:
    """Names of the features that hold of a section."""
    context, tag, a, b, c, links, size, part, twins, blocks, opens = known
    names = [f"in {t}" for t in context]
    names += [f"place {a} {b}", f"article {c}", f"article {c} {a}", f"{tag} {a}", f"{tag} {b}", f"links {links}", f"links {links} {a}", f"opens {opens} {a}", f"opens {opens} {tag} {a}"]
    return [*names, f"size {size} {a}", f"part {part}", f"twins {twins} {tag} {a}", f"blocks {blocks} {a}"]


def block_features(inside: tuple[str, ...], links: int, size: int, alone: bool, place: str) -> list[str]:
    """Names of the features that hold of a block in a section at ``place``."""
    names = [f"tag {t}" for t in inside] if inside else ["loose"]
    last = inside[-1] if inside else "loose"
    return [*names, f"{last} at {place}", f"linked {links}", f"linked {links} at {place}", f"linked {links} {last}", f"words {size}", f"words {size} {last}", f"alone {alone} {place}"]


def _of_block(page: Page, block: Block, known: list[tuple]) -> tuple:
    return block.inside, _share(block.linked, block.words), _step(block.words), page.sections[block.section].blocks == 1, known[block.section][2]


@dataclass
class Weights:
    """Log-odds of places and tags."""

    bias: float
    place: dict[str, float]
    tag: dict[str, float]

    def scores(self, page: Page) -> tuple[list[float], int]:
        """Score of each token, and the section that the article is likely to be in."""
        most, head = _likely(page)
        sections, known = page.sections, _known(page)
        sums: dict[tuple, float] = {}

        def total(key: tuple, features) -> float:
            if key not in sums:
                sums[key] = sum([self.place.get(n, 0.0) for n in features()])
            return sums[key]

        out = []
        for t in page.tokens:
            if not isinstance(t, Block):
                out.append(self.tag.get(t, -0.05))
                continue
            about, key = known[t.section], _of_block(page, t, known)
            out.append((self.bias + total(about, lambda about=about: section_features(about)) + total(key, lambda key=key: block_features(*key))) * t.words)
        return out, most if head < 0 or _place(most, head, sections) != "in" else head


def learn(pages: list[tuple[str, list[str]]], steps: int = 12) -> Weights:
    """Weights from pages with their content blocks, by logistic regression on places and tag counts.

    A block is content when its text is among the page's labelled ones.
    """
    seen: dict[tuple, list[int]] = {}  # blocks in one kind of place: how many, and how many are content
    inside: dict[str, int] = {}
    outside: dict[str, int] = {}
    for source, blocks in pages:
        page, wanted = read(source), set(blocks)
        known = _known(page)
        good = [i for i, t in enumerate(page.tokens) if isinstance(t, Block) and t.text in wanted]
        for i, t in enumerate(page.tokens):
            if isinstance(t, Block):
                n = seen.setdefault((known[t.section], _of_block(page, t, known)), [0, 0])
                n[0] += 1
                n[1] += t.text in wanted
            else:
                side = inside if good and good[0] <= i <= good[-1] else outside
                side[t] = side.get(t, 0) + 1
    rows = [section_features(section) + block_features(*block) for section, block in seen]
    vocabulary = sorted({n for r in rows for n in r})
    at = {n: i for i, n in enumerate(vocabulary)}
    x = np.zeros((len(rows), len(vocabulary) + 1), dtype=np.float32)
    x[:, -1] = 1
    for i, r in enumerate(rows):
        x[i, [at[n] for n in r]] = 1
    count, target = np.array(list(seen.values()), dtype=float).reshape(-1, 2).T
    w = np.zeros(len(vocabulary) + 1)
    for _ in range(steps):  # Newton-like steps with a ridge
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        ridge = np.full(len(w), 0.01)
        h = ((x * (count * np.maximum(p * (1 - p), 1e-4))[:, None].astype(np.float32)).T @ x).astype(np.float64) + np.diag(ridge)
        step = np.linalg.solve(h, x.T @ (target - count * p) - ridge * w)
        w += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-3:
            break
    total_in, total_out = sum(inside.values()) + 1, sum(outside.values()) + 1
    tags = {t: float(np.clip(np.log((inside.get(t, 0) + 0.5) / total_in) - np.log((outside.get(t, 0) + 0.5) / total_out), -1.0, -0.05)) for t in {*inside, *outside}}
    return Weights(float(w[-1]), {n: float(w[at[n]]) for n in vocabulary}, tags)


def best_region(scores: list[float]) -> tuple[int, int]:
    """Half-open bounds of the contiguous stretch with the highest positive sum; the earliest and shortest among equals; (0, 0) if none is positive."""
    best, lo, hi = 0.0, 0, 0
    total, start = 0.0, 0
    for i, s in enumerate(scores):
        if total <= 0:
            total, start = 0.0, i
        total += s
        if total > best:
            best, lo, hi = total, start, i + 1
    return lo, hi


def main_text(source: str | None, weights: Weights) -> str:
    """Text of the best region, blocks joined by one blank; "" for null or empty pages, or pages without content."""
    if not source:
        return ""
    page = read(source)
    scores, article = weights.scores(page)
    sums = [0.0]
    for s in scores:
        sums.append(sums[-1] + s)
    leave = 0  # end of the island that we are in
    islands = {lo: hi for lo, hi, around in sorted(page.groups, key=lambda g: g[1]) if article <= around <= page.sections[article].last and sums[hi] < sums[lo]}
    kept = []
    for i in range(len(scores)):
        leave = max(leave, islands.get(i, 0))
        if i >= leave:
            kept.append(i)
    lo, hi = best_region([scores[i] for i in kept])
    return " ".join([t.text for t in (page.tokens[i] for i in kept[lo:hi]) if isinstance(t, Block)])


@lru_cache(maxsize=1)
def standard_weights() -> Weights:
    """Weights learnt on the labelled pages of this package."""
    return learn(labelled_pages())


def _extract(weights, html_col: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(p, weights.value) for p in batch.column(html_col).to_pylist()]
            keep = [i for i, n in enumerate(batch.schema.names) if n != html_col]
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in keep], pa.array(texts, pa.string())], names=[*[batch.schema.names[i] for i in keep], "text"])

    return run


def extract_content(pages: DataFrame, keep: list[str], html_col: str = "html", weights: Weights | None = None) -> DataFrame:
    """``keep`` columns of every row plus ``text``, its main text.

    Null and empty pages give an empty text; null and repeated keys keep their
    rows; an empty table gives no rows.  Without ``weights`` they are learnt on
    the labelled pages that this package makes.
    """
    spark = pages.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(weights or standard_weights())
    cols = pages.select(*keep, F.col(html_col).cast("string").alias("__html"))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cols.schema.fields if f.name != "__html")
    return cols.mapInArrow(kernel.tidy(_extract(shared, "__html")), f"{schema}, text string")


def op10_html_content(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of all ``pages``."""
    out = extract_content(spark.read.parquet(f"{sf_dir}/pages.parquet"), ["page_id", "url"])
    return out.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
