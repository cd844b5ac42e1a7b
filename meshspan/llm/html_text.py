"""Main text of web pages by two-pass block rules.

Pass one looks at each block alone: its place in the page (navigation, footers, forms, adverts,
comments; article or main), its link density, its length, and its density of function words. Pass two
lets blocks that are too short to judge take the label of the nearest decided neighbours.
"""

from __future__ import annotations

import html
import re
from bisect import bisect_right
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Frequent function words.
STOP_WORDS = frozenset(
    """the of and to in is that it was for on are as with be by at this from or an not have but which his they he she you we
    der die das und ist von den mit zu ein eine nicht für auf im sich des dem auch als es an werden aus er hat dass sie nach
    le la les et de des du un une est que qui dans pour par sur pas au avec ce il elle ne en plus se son sont ou
    el los las y una por con para es se lo del al como más pero sus no su o este""".split()
)
# Elements by role.
RAW = "script|style|noscript|template|svg|math|iframe|object|canvas|textarea|select|audio|video"
BLOCKS = frozenset(
    """address article aside blockquote body caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3
    h4 h5 h6 header hr html legend li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul head title""".split()
)
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
APART = frozenset("nav footer aside form dialog menu button head title fieldset".split())
CLOSES_P = BLOCKS - {"html", "body", "head", "title"}
HINT_APART = re.compile(
    r"(?:^|[\s_-])(?:ads?|adverts?|advertisement|adsense|banner|promo(?:tion)?s?|sponsor(?:ed)?|sidebar|navbar|nav|navigation|menu|breadcrumbs?|"
    r"masthead|site-header|page-header|topbar|header|footer|site-footer|cookies?|consent|gdpr|notice|notification|alert|popup|modal|overlay|newsletter|subscribe|"
    r"subscription|signup|login|social|share|sharing|related|recommended|recommendations|comments?|comment-list|replies|respond|disqus|widget|"
    r"toolbar|pagination|pager|copyright|disclaimer|skip-link|trending|popular|outbrain|taboola)(?:$|[\s_-])",
    re.I,
)
HINT_MAIN = re.compile(r"(?:^|[\s_-])(?:article(?:-?body)?|post(?:-?(?:content|body))?|entry(?:-?content)?|story(?:-?body)?|main-?content|page-?content|content)(?:$|[\s_-])", re.I)
#: Elements of this name, and no other, hold articles beside the page's own.
HINT_OTHERS = re.compile(r"(?:related|recommended|recommendations|trending|popular|outbrain|taboola)(?:[-_](?:articles?|posts?|stories|items?|content|links?|list|box|section|widget))?(?:\s+(?:related|recommended|trending|popular)(?:[-_]\w+)?)*$", re.I)
# Elements within which an open item ends at the next, and what ends at which.
SCOPES = ("table", "ul", "ol", "dl", "div", "section", "article", "main", "aside", "nav", "footer", "header", "td", "th", "blockquote", "form")
ALIKE = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th")}
HEADED = ("p", "h1", "h2", "h3", "h4", "h5", "h6")
ROLE_APART = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar".split())

_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?\]\]>|<({RAW})\b(?:\"[^\"]*\"|'[^']*'|[^'\">])*?(?:/>|>.*?(?:</\1\s*>|\Z))|"
    r"<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^'\"<>])*)/?>|<[!?][^>]*>",
    re.I | re.S,
)
_ATTRIBUTE = re.compile(r"([a-zA-Z_:][-\w:.]*)\s*(?:=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_SPACE = re.compile(r"\s+")
_SENTENCE = re.compile(r"[^\W\d_]{2}[.!?…;»”\"')]*[.!?…](?:\s|$|[»”\"')])|[。！？।؟۔]")
_WORD = re.compile(r"[^\W\d_]+")

SHORT, LONG = 70, 200  # code points
LINKED = 0.33  # a block with a greater share of link text is no article text
DENSE, SPARSE = 0.30, 0.15  # shares of function words


@dataclass
class Block:
    text: str
    link_chars: int
    apart: bool
    article: bool
    main: bool
    heading: bool
    label: str = ""


def _marks(tag: str, attributes: str) -> tuple[bool, bool, bool, bool, bool]:
    """(apart by kind, apart by name, article, main, a list of other articles) of an element. A layout's name may
    mention a sidebar that is only a part of it: an article or main element inside takes its own way, but not out of
    what lists other articles."""
    apart, named, article, main, side = tag in APART, False, tag == "article", tag == "main", False
    if attributes and tag not in ("html", "body"):
        own = {m[1].lower(): m[2] or m[3] or m[4] or "" for m in _ATTRIBUTE.finditer(attributes)}
        names = f"{own.get('class', '')} {own.get('id', '')}"
        role = own.get("role", "").lower()
        if role in ROLE_APART or "hidden" in own or own.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", own.get("style", ""), re.I):
            apart = True
        if "comment" in names.lower() or "replies" in names.lower():
            apart = apart or HINT_APART.search(names) is not None
        elif tag not in ("article", "main", "a", "span", "b", "i", "em", "strong"):
            named = names.strip() != "" and HINT_APART.search(names) is not None
            side = HINT_OTHERS.match(names.strip()) is not None
        if role in ("main", "article") or own.get("itemprop") == "articleBody" or (tag in ("div", "section") and HINT_MAIN.search(names)):
            main = True
    return apart, named, article, main, side


def blocks_of(page: str) -> list[Block]:
    """Text blocks of a page in order."""
    out: list[Block] = []
    stack: list[tuple[str, bool, bool, bool, bool, bool, bool]] = []  # tag, apart, article, main, link, heading, named apart
    places: dict[str, list[int]] = {}  # where each tag stands open in the stack
    words: list[str] = []
    linked = 0

    def last(tags: tuple[str, ...]) -> int:
        return max((places[t][-1] for t in tags if places.get(t)), default=-1)

    def first_after(tags: tuple[str, ...], limit: int) -> int:
        """Lowest open element of these tags above a place of the stack."""
        found = [places[t][at] for t in tags if places.get(t) and (at := bisect_right(places[t], limit)) < len(places[t])]
        return min(found, default=-1)

    def flush():
        nonlocal linked
        text = _SPACE.sub(" ", "".join(words)).strip()
        words.clear()
        if text:
            apart, article, main, _, heading, named = stack[-1][1:] if stack else (False,) * 6
            out.append(Block(text, min(linked, len(text)), apart or named, article, main, heading))
        linked = 0

    def say(raw: str):
        nonlocal linked
        if raw:
            text = html.unescape(raw)
            words.append(text)
            if stack and stack[-1][4]:
                linked += len(_SPACE.sub(" ", text).strip())

    def close(to: int):
        if any(s[0] in BLOCKS for s in stack[to:]):
            flush()
        for s in stack[to:]:
            places[s[0]].pop()
        del stack[to:]

    at = 0
    for m in _TOKEN.finditer(page):
        say(page[at : m.start()])
        at = m.end()
        tag = (m[3] or "").lower()
        if not tag:
            if m[1] and m[1].lower() in ("textarea", "select", "iframe", "video", "audio", "object"):
                words.append(" ")
            continue
        if m[2]:
            found = last((tag,))
            if found >= 0:
                close(found)
            elif tag in BLOCKS:
                flush()
            continue
        if tag == "br":
            words.append(" ")
            continue
        if tag in BLOCKS:
            flush()
            limit = last(SCOPES)
            ends = first_after(ALIKE.get(tag, ()) + (HEADED if tag in CLOSES_P else ()), limit)
            if tag == "body" and places.get("head"):
                ends = places["head"][0]
            if tag in ("td", "th", "tr") and limit >= 0 and stack[limit][0] in ("td", "th"):
                ends = limit
            if ends >= 0:
                close(ends)
        if tag in VOID:
            continue
        apart, named, article, main, side = _marks(tag, m[4])
        above = stack[-1] if stack else ("", False, False, False, False, False, False)
        apart = apart or side
        named = named or (above[6] and tag not in ("article", "main"))
        if tag == "header" and not (above[2] or above[3]):
            apart = True
        places.setdefault(tag, []).append(len(stack))
        stack.append((tag, above[1] or apart, above[2] or article, above[3] or main, above[4] or tag == "a", above[5] or tag in ("h1", "h2", "h3", "h4", "h5", "h6"), named))
    say(page[at:])
    flush()
    return out


def _prose(block: Block) -> bool:
    """Whether a block without listed function words reads like sentences: hardly any links, and a sign that
    ends a sentence. Its language may be one of those that the list lacks."""
    return block.link_chars <= 0.1 * len(block.text) and "©" not in block.text and _SENTENCE.search(block.text) is not None


def _alone(block: Block, inside: bool, has_inside: bool) -> str:
    """Pass one: good, bad, near (good if a neighbour is) or short (undecided)."""
    n = len(block.text)
    if block.apart or (has_inside and not inside):
        return "bad"
    if block.link_chars > LINKED * n:
        return "bad"
    if block.heading or n < SHORT:
        return "short" if inside or (block.link_chars == 0 and "©" not in block.text) else "bad"
    words = _WORD.findall(block.text.lower())
    density = sum(w in STOP_WORDS for w in words) / len(words) if words else 0.0
    if density >= DENSE:
        return "good" if n >= LONG or inside else "near"
    if inside:
        return "near"
    return "near" if density >= SPARSE or _prose(block) else "bad"


def _runs(blocks: list[Block], first: list[str]) -> set[int]:
    """Near blocks of the runs, short blocks between them included, that are long enough together."""
    out: set[int] = set()
    run: list[int] = []
    for i, label in enumerate([*first, "bad"]):
        if label in ("near", "short"):
            run.append(i)
            continue
        if sum(len(blocks[j].text) for j in run if not blocks[j].heading) >= LONG:
            out |= {j for j in run if first[j] == "near"}
        run = []
    return out


def labelled(page: str) -> list[Block]:
    """Blocks with their final labels, good or bad."""
    blocks = blocks_of(page)
    wide = "article" if any(b.article and not b.apart for b in blocks) else "main" if any(b.main and not b.apart for b in blocks) else ""
    inside = [bool(wide) and getattr(b, wide) and not b.apart for b in blocks]
    first = [_alone(b, i, bool(wide)) for b, i in zip(blocks, inside, strict=True)]
    decided_before, decided_after = _nearest(first, ("good", "bad"))
    good = set()
    for i, label in enumerate(first):
        if label == "near":  # joins good text on either side, or what its element says
            sides = {first[j] for j in (decided_before[i], decided_after[i]) if j >= 0}
            if inside[i] or "good" in sides:
                good.add(i)
    good |= _runs(blocks, first)
    if not good and "good" not in first:  # nothing better on the page
        good = {i for i, label in enumerate(first) if label == "near"}
        if not good:  # a page of short paragraphs, or of a language without listed words
            good = _longest_run(blocks, first)
    second = ["good" if i in good else "bad" if x == "near" else x for i, x in enumerate(first)]
    before, after = _nearest(second, ("good", "bad"))
    for i, block in enumerate(blocks):
        block.label = second[i]
        if second[i] != "short":
            continue
        # an undecided block of an article asks only inside it
        found = [(abs(j - i), second[j]) if j >= 0 and (not inside[i] or inside[j]) else None for j in (before[i], after[i])]
        near = [x for x in found if x]
        if inside[i]:
            block.label = min(near, key=lambda x: (x[0], x[1] != "good"))[1] if near else "good"
        elif len(near) == 2 and near[0][1] != near[1][1]:
            block.label = "good" if block.heading and near[1][1] == "good" else min(near, key=lambda x: (x[0], x[1] == "good"))[1]
        else:
            block.label = near[0][1] if near else "bad"
    return blocks


def _nearest(labels: list[str], wanted: tuple[str, ...]) -> tuple[list[int], list[int]]:
    """For each place the nearest one before and after it with a wanted label, or -1: one sweep each way."""

    def swept(order) -> list[int]:
        out, seen = [-1] * len(labels), -1
        for i in order:
            out[i] = seen
            if labels[i] in wanted:
                seen = i
        return out

    return swept(range(len(labels))), swept(range(len(labels) - 1, -1, -1))


def _longest_run(blocks: list[Block], first: list[str]) -> set[int]:
    """The longest stretch of unlinked blocks beside each other that are not named apart, if it is as long as an
    article's paragraph."""
    best, run = [], []
    for i, block in enumerate([*blocks, None]):
        if block is not None and not block.apart and block.link_chars <= 0.1 * len(block.text) and "©" not in block.text:
            run.append(i)
            continue
        if sum(len(blocks[j].text) for j in run) > sum(len(blocks[j].text) for j in best):
            best = run
        run = []
    return set(best) if sum(len(blocks[j].text) for j in best) >= SHORT else set()


def main_text(page: str | None) -> str:
    """Good blocks joined by newlines; null and empty pages give an empty string."""
    return "\n".join(b.text for b in labelled(page or "") if b.label == "good")


def extracted(pages: DataFrame) -> DataFrame:
    """(page_id, url, text, n_chars) of every row of ``pages(page_id, url, html)``. Null html is empty;
    a page of no article text gives an empty string; repeated rows come back as often as they came;
    other columns are ignored."""
    types = pa.schema([("page_id", pa.int64()), ("url", pa.string()), ("text", pa.string()), ("n_chars", pa.int64())])

    def run(batches):
        for batch in batches:
            source = batch.column("html")
            texts = [main_text(source[i].as_py()) for i in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], schema=types)

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")
