"""Main text of web pages by the maximum-scoring subsequence of tags and words.

A page is a sequence of text runs and tags.  Words score positive, or negative
inside links and inside parts that name themselves as menus, adverts, notices,
comments and the like, which are left out of the text in any case; tags score negative, each by the share
of its kind that stands outside the main text of labelled pages.  One linear
scan finds the contiguous region of the highest sum.  Where an article or main
element holds the region, all of that element is taken.

A part names itself by a whole class, id or role ("ad", "site-footer"), never by
one word of a longer name ("search-results-analysis"), and a heading never does.
Names that articles use too ("related", "discussion") only lower the score of a
part's words, unless half of its words are links; a section may bear them freely.
"""

from __future__ import annotations

import html as entities
import math
import re
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import thin

#: Pages that weights are learnt from, at most: those of the smallest hashes.
SAMPLE_PAGES = 2_000

_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<(script|style|noscript|template|svg|iframe|textarea|select|object|canvas|title)\b(?:[^<>\"']|\"[^\"]*\"|'[^']*')*>.*?(?:</\1\s*>|\Z)|<(/?)([a-zA-Z][\w:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)>|<[!?][^>]*>|<(/?)([a-zA-Z][\w:-]*)([^>]*)>",
    re.S | re.I,
)
_NAMES = re.compile(r"""\b(class|id|role|aria-label|data-role|data-component)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none|visibility\s*:\s*hidden""", re.I)
_CAMEL = re.compile(r"([a-z0-9])([A-Z])")

#: Kinds of elements.
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody tfoot thead title tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
OUTSIDE = frozenset("nav footer aside form menu dialog head button header".split())
#: Elements that no name takes away.
UNNAMED = frozenset("html body article main h1 h2 h3 h4 h5 h6 hgroup blockquote pre code table thead tbody tfoot tr td th caption figure figcaption b i em strong u s sub sup br hr img dl dt dd".split())
CLEAR = frozenset(
    "ad ads adv advert adverts advertisement advertisements advertising adsense banner sponsor sponsored promo sidebar sidebars nav navbar navigation menu menubar breadcrumb breadcrumbs crumbs pagination pager footer footnav masthead topbar toolbar comment comments commentlist respond disqus cookie cookies consent gdpr notice notices notification popup modal overlay lightbox share sharing social subscribe subscription newsletter signup searchbox widget widgets skiplink copyright".split()
)
UNSURE = frozenset("aside side rail toc foot header replies reply discussion alert follow login search related recommended recommendations trending popular promoted promotion legal disclaimer tags taglist byline meta skip complementary contentinfo".split())
#: Words that may stand beside a name within one class, and classes that mark content.
BESIDE = frozenset("site page main top bottom left right area section box wrapper wrap container block list posts post articles article links link item items inner outer column col bar row group panel region zone unit primary secondary global mobile desktop content form body text thread buttons policy message reader user users".split())
CONTENT = frozenset("entry content article story post text body prose hentry".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert menu menubar toolbar".split())


@dataclass
class Weights:
    """Score of a word, of a word in a link, of one under an unsure name, of one in a named part (down to that of a whole part), and of tags."""

    word: float = 1.0
    linked: float = -0.5
    unsure: float = -0.3
    named: float = -1.0
    named_part: float = -2.0
    other_tag: float = -0.4
    tags: dict[str, float] = field(default_factory=dict)


def _kind(name: str) -> str:
    """What one class says: clear, unsure, content or nothing.  All its words must be names or words beside them."""
    words = [x for x in re.split(r"[^a-z0-9]+", _CAMEL.sub(r"\1 \2", name).lower()) if x and not x.isdigit()]
    if all(x in CLEAR or x in UNSURE or x in BESIDE for x in words):
        if CLEAR.intersection(words):
            return "clear"
        if UNSURE.intersection(words):
            return "unsure"
    return "content" if words and CONTENT.issuperset(words) else ""


def _named(tag: str, attributes: str, in_main: bool) -> str:
    """Whether an element is left out ("clear"), doubted ("unsure") or neither."""
    if tag in OUTSIDE:
        return "" if tag == "header" and in_main else "clear"
    if not attributes:
        return ""
    if _HIDDEN.search(attributes) and tag not in ("html", "body"):
        return "clear"
    if tag in UNNAMED:
        return ""
    kinds = set()
    for key, a, b, c in _NAMES.findall(attributes):
        value = a or b or c
        if key.lower() == "role":
            kinds |= {"clear" for r in value.lower().split() if r in ROLES}
        else:
            kinds |= {_kind(n) for n in (["-".join(value.split())] if key.lower() == "aria-label" else value.split())}
    if "clear" in kinds:
        return "clear"
    return "unsure" if "unsure" in kinds and "content" not in kinds and tag != "section" else ""


@dataclass
class Item:
    """A text run, or a tag that starts or ends an element."""

    text: str = ""
    tag: str = ""
    words: int = 0
    linked: bool = False
    named: bool = False
    unsure: bool = False


def items(page: str) -> tuple[list[Item], list[tuple[int, int]]]:
    """The items of a page, and the item ranges of its article and main elements."""
    out: list[Item] = []
    at, link, skip, depth, main = 0, 0, "", 0, []
    ranges: list[tuple[int, int]] = []
    skip_from = 0
    doubted: list[tuple[str, int, int]] = []  # open parts of unsure names: tag, depth of that tag, first item
    parts: list[tuple[int, int]] = []

    def text(run: str) -> None:
        if run:
            out.append(Item(run, "", len(run.split()), link > 0, bool(skip)))

    for m in _TAG.finditer(page):
        text(page[at : m.start()])
        at = m.end()
        tag = (m[3] or m[6] or "").lower()
        if not tag:
            out.append(Item(tag="!", named=bool(skip)))
            continue
        closing, attributes = bool(m[2] or m[5]), m[4] or m[7] or ""
        if skip:
            if tag == skip:
                depth += -1 if closing else tag not in VOID and not attributes.rstrip().endswith("/")
            if depth <= 0:
                out.append(Item(tag="/" + tag, named=True))
                skip = ""
                continue
            if tag in ("article", "main") and not closing and not main and skip not in ("article", "main", "aside", "nav", "footer", "form"):
                skip = ""  # what held the skipped part was never closed
            else:
                out.append(Item(tag=("/" if closing else "") + tag, named=True))
                continue
        if tag not in VOID and not attributes.rstrip().endswith("/"):
            kind = "" if closing else _named(tag, attributes, bool(main))
            if kind == "clear":
                skip, depth, skip_from = tag, 1, len(out)
                out.append(Item(tag=tag, named=True))
                continue
            if kind == "unsure":
                doubted.append((tag, 1, len(out)))
            elif doubted and doubted[-1][0] == tag:
                name, open_, first = doubted.pop()
                open_ += -1 if closing else 1
                if open_:
                    doubted.append((name, open_, first))
                else:
                    parts.append((first, len(out) + 1))
        if tag == "a":
            link = 0 if closing else 1
        if tag in ("article", "main"):
            if not closing:
                main.append(len(out))
            elif main:
                ranges.append((main.pop(), len(out)))
        out.append(Item(tag=("/" if closing else "") + tag))
    text(page[at:])
    ranges += [(a, len(out)) for a in main]
    for first, end in parts:  # a part that is never closed says nothing
        own = [p for p in out[first:end] if not p.named]
        words = sum(p.words for p in own)
        drop = sum(p.words for p in own if p.linked) * 2 >= words
        for p in own:
            p.named, p.unsure = drop, not drop
    if skip and skip not in ("head", "footer", "nav") and not any(a <= skip_from < b for a, b in ranges):
        # An element that names itself so but is never closed: only its first run goes.
        seen = False
        for item in out[skip_from:]:
            if not item.tag and not seen:
                seen = True
            elif seen:
                item.named = False
    return out, ranges


def region(parts: list[Item], w: Weights) -> tuple[int, int]:
    """Start and end of the items of the highest sum; an empty range where no sum is positive."""
    best, best_at, total, start, part = 0.0, (0, 0), 0.0, 0, 0.0
    for i, p in enumerate(parts):
        if p.named:  # an advert amid the text mustn't end it, however long
            step = max(p.words * w.named, w.named_part - part)
            total, part = total + step, part + step
        elif p.tag:
            total, part = total + w.tags.get(p.tag.lstrip("/"), w.other_tag), 0.0
        elif p.words:
            total, part = total + p.words * (w.linked if p.linked else w.unsure if p.unsure else w.word), 0.0
        if total <= 0:
            total, start = 0.0, i + 1
        elif total > best:
            best, best_at = total, (start, i + 1)
    return best_at


def extract(page: str | None, w: Weights) -> str:
    """The main text: blocks in page order, one line each; empty for null and where nothing scores."""
    if not page:
        return ""
    parts, mains = items(page)
    a, b = region(parts, w)
    if a >= b:
        return ""
    around = [(x, y) for x, y in mains if sum(p.words for p in parts[max(a, x) : min(b, y)] if not p.named) * 2 > sum(p.words for p in parts[a:b] if not p.named)]
    if around:
        a, b = min(around, key=lambda r: (r[1] - r[0], r))
    lines: list[str] = []
    run: list[str] = []

    def flush() -> None:
        line = " ".join("".join(run).split())
        if line:
            lines.append(line)
        run.clear()

    for p in parts[a:b]:
        name = p.tag.lstrip("/")
        if name in BLOCKS:
            flush()
        elif name in ("td", "th"):
            run.append(" ")
        elif not p.tag and not p.named:
            run.append(entities.unescape(p.text))
    flush()
    return "\n".join(lines)


def _tag_counts(column: str):
    def run(batches):
        for b in batches:
            tally: dict[str, list[int]] = {}
            for page in b.column(column).to_pylist():
                parts, mains = items(page or "")
                outer = [(x, y) for x, y in mains if not any(c <= x and y <= d and (c, d) != (x, y) for c, d in mains)]
                if len(outer) != 1:
                    continue  # not labelled
                (x, y), = outer
                for i, p in enumerate(parts):
                    if p.tag:
                        tally.setdefault(p.tag.lstrip("/"), [0, 0])[x <= i <= y and not p.named] += 1
            rows = [(t, *n) for t, n in tally.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.string()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.int64())], names=["tag", "outside", "inside"])

    return run


def fit(pages: DataFrame, id: str = "page_id", html: str = "html", sample_pages: int = SAMPLE_PAGES) -> Weights:
    """Tag weights from at most `sample_pages` pages; one article or main element labels a page.

    A tag costs between 0.02, if labelled pages have it inside only, and 1, if
    outside only; unknown tags keep the default.
    """
    hashed = pages.select(F.col(html).alias("html"), F.xxhash64(F.col(id), F.col(html)).alias("h")).where("html is not null")
    sample = thin(hashed, "h", hashed.count(), sample_pages).orderBy("h").limit(sample_pages)
    counts = sample.select("html").mapInArrow(_tag_counts("html"), "tag string, outside long, inside long").groupBy("tag").agg(F.sum("outside").alias("o"), F.sum("inside").alias("i"))
    w = Weights()
    for tag, o, i in counts.orderBy("tag").collect():  # the tag names of the sample
        share = (o + 0.5) / (o + i + 1)
        w.tags[tag] = -(0.02 + 0.98 * share * math.tanh((o + i) / 5))
    return w


def main_text(pages: DataFrame, weights: Weights, id: str = "page_id", html: str = "html", keep: tuple[str, ...] = ()) -> DataFrame:
    """(id, columns of `keep`, text, n_chars) for every row.

    A null or empty page, and one where nothing scores, has an empty text and 0
    characters.  Of regions of one sum the first is taken.  Repeated rows come
    back as often; an empty table gives no rows; a page goes through one scan
    whatever its length.  Columns of `keep` named text or n_chars are refused.
    """
    if {"text", "n_chars"} & {id, *keep}:
        raise ValueError("text and n_chars are names of results")
    names = [id, *keep]
    schema = ", ".join(f"`{c}` {pages.schema[c].dataType.simpleString()}" for c in names) + ", text string, n_chars long"

    def run(batches):
        for b in batches:
            texts = [extract(p, weights) for p in b.column(len(names)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(names)], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[*names, "text", "n_chars"])

    return pages.select(*names, F.col(html).alias("_html")).mapInArrow(run, schema)
