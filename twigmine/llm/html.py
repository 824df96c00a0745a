"""Main text of web pages by two passes of block rules.

Pass one labels each block by itself: good, near, short or bad, from its stop-word density, its length and its link density.  What
holds the block is one more piece of evidence: it moves the label up or down, and where the rules apply at all.
Pass two gives what is still open, the short and the near blocks, the label of the nearest decided neighbours.
"""

from __future__ import annotations

import html as entities
import re
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import DataFrame

# Frequent function words of English, German, French and Spanish.
STOP_WORDS = frozenset(
    "the of and to in is that for it was with as on be by at this are from or an have not but which they you his her "
    "der die das und den von zu mit sich des auf für ist im dem nicht ein eine als auch es an werden aus er hat dass "
    "le la les de des du et en un une que qui dans pour par sur au avec pas est il elle ce se plus ou "
    "el los las y del que se por con una su para es al lo como más pero sus este".split()
)
# Elements that begin and end blocks; that hold no article text; whose content is no markup.
BLOCK = frozenset("address article aside blockquote body caption center col colgroup dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section select summary table tbody td template textarea tfoot th thead title tr ul".split())
LEAF = frozenset("p li dd dt td th tr h1 h2 h3 h4 h5 h6 option".split())
AWAY = frozenset("nav footer aside form head menu dialog button select template fieldset noscript object svg canvas audio video map".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes template svg math".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
# Words of class, id and role that mark what is no article.
HINTS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup login comment comments respond disqus reply replies sidebar aside widget widgets related recommended share sharing social breadcrumb breadcrumbs menu nav navbar navigation pager pagination toolbar footer masthead contentinfo complementary search searchbox dialog toc skip hidden".split())
#: Those that mark even an article element as none of the page's own.
NO_STORY = frozenset("ad ads advert advertisement sponsor sponsored promo promotion comment comments reply replies related recommended".split())
#: A whole tag: name, then names, equal signs with quoted or plain values, and slashes.  Nothing is tried twice.
TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:[^\s>=]++|\s++|=\s*+(?:\"[^\"]*+\"|'[^']*+')?+)*+)>")
OPENS = re.compile(r"</?[a-zA-Z]")
NAME = re.compile(r"</?([a-zA-Z][^\s/>]*+)")
ATTRIBUTE = re.compile(r"([a-zA-Z-]++)\s*+=\s*+(?:\"([^\"]*+)\"|'([^']*+)'|([^\s\"'>]++))")
HIDDEN = re.compile(r"(?:^|\s)hidden(?=[\s/]|$)")
NO_SHOW = re.compile(r"display\s*+:\s*+none|visibility\s*+:\s*+hidden", re.I)
CUT = re.compile(r"[^a-z0-9]+")
HUMP = re.compile(r"([a-z])([A-Z])")
WORD = re.compile(r"\w+")

#: Rules of the first pass: characters, share of links, and shares of stop words for lists of some twenty-five words a language.
SHORT, LONG, MOST_LINKS, FEW_STOPS, MANY_STOPS = 70, 200, 0.2, 0.10, 0.15
#: The share of links from which a block is bad even in an article, if it has few stop words, and the words a lone link may have.
LINKS_IN_STORY, LONE_LINK = 0.5, 3
#: Labels of the first pass in their order; short ones stand beside it.
BAD, NEAR, GOOD, BRIEF = 0, 1, 2, 3
#: Steps by which the holder moves a label: an article, a page whose article is elsewhere, a holder of what is no article.
IN_STORY, ELSEWHERE, IN_AWAY = 1, -1, -3


class Block(NamedTuple):
    """A block's text, its characters inside links, whether it or a holder is marked as no article, and the numbers of its article (0: none) and its holder."""

    text: str
    linked: int
    away: bool
    story: int
    holder: int


def words_of(value: str) -> set[str]:
    """Words of a class, id or role; what a page has, or has not, (has-sidebar) is left out."""
    words = CUT.split(HUMP.sub(r"\1 \2", value).lower())
    return {w for k, w in enumerate(words) if not (k and words[k - 1] in ("has", "with", "no", "without"))}


def hinted(attributes: str, hints: frozenset = HINTS) -> bool:
    """Whether an element's class, id, role or style mark it as no article."""
    if "=" not in attributes and "hidden" not in attributes:
        return False
    for name, a, b, c in ATTRIBUTE.findall(attributes):
        value, name = a or b or c, name.lower()
        if name in ("class", "id", "role") and any(not hints.isdisjoint(words_of(part)) for part in value.split()):
            return True
        if name == "aria-hidden" and value.lower() == "true" or name == "style" and NO_SHOW.search(value):
            return True
    return bool(HIDDEN.search(ATTRIBUTE.sub("", attributes)))


def tokens_of(page: str):
    """Runs of text and tags in page order: (text, "", False, "") or ("", name, whether it ends, attributes).

    Each character is read a bounded number of times, whatever is left open.  Comments, declarations and the content of RAW elements
    are left out.  A tag that the page's end cuts off is no text.  If quotes that never close swallow the rest of the page, this
    and all later tags end at their first ">".
    """
    at, n, loose = 0, len(page), False
    while at < n:
        lt = page.find("<", at)
        if lt < 0:
            yield page[at:], "", False, ""
            return
        if lt > at:
            yield page[at:lt], "", False, ""
        if page.startswith("<!--", lt):
            end = page.find("-->", lt + 4)
            at = end + 3 if end >= 0 else n
        elif page.startswith(("<!", "<?"), lt):
            end = page.find(">", lt)
            at = end + 1 if end >= 0 else n
        elif not OPENS.match(page, lt):
            yield "<", "", False, ""
            at = lt + 1
        else:
            m = None if loose else TAG.match(page, lt)
            if m:
                ends, name, attributes, at = bool(m[1]), m[2].lower(), m[3], m.end()
            else:
                end = page.find(">", lt)
                if end < 0:
                    return
                loose = True
                m = NAME.match(page, lt, end)
                ends, name, attributes, at = page[lt + 1] == "/", m[1].lower(), page[m.end() : end], end + 1
            if not ends and name in RAW and not attributes.endswith("/"):
                found = re.compile(f"</{name}(?=[\\s/>])[^>]*+>?", re.I).search(page, at)
                at = found.end() if found else n
                yield "", name, True, ""
            else:
                yield "", name, ends, attributes


def blocks_of(page: str) -> list[Block]:
    """Blocks in page order."""
    out: list[Block] = []
    parts: list[str] = []
    # Open holders: name, whether any of them marks what is no article, number of the article, own number.
    stack: list[tuple[str, bool, int, int]] = [("", False, 0, 0)]
    opened: dict[str, int] = {}
    stories = holders = linked = 0
    in_link = leaf_away = False

    def close() -> None:
        nonlocal linked
        if parts:
            text = " ".join(entities.unescape("".join(parts)).split())
            if text:
                _, away, story, holder = stack[-1]
                out.append(Block(text, linked, away or leaf_away, story, holder))
            parts.clear()
        linked = 0

    for text, name, ends, attributes in tokens_of(page):
        if text:
            parts.append(text)
            linked += len(text) if in_link else 0
        elif name == "br":
            parts.append(" ")
        elif name == "a":
            in_link = not ends
        elif name in LEAF:
            close()
            in_link = False
            leaf_away = not ends and (name == "option" or hinted(attributes))
        elif name in BLOCK or name in AWAY:
            close()
            in_link = leaf_away = False
            if ends:
                if opened.get(name):
                    while True:
                        gone = stack.pop()[0]
                        opened[gone] -= 1
                        if gone == name:
                            break
            elif name not in VOID:
                _, away, story, _ = stack[-1]
                if name in ("article", "main") and not story:
                    stories += 1
                    story = stories
                away = away or name in AWAY or name == "header" and not story or name not in ("html", "body", "main") and hinted(attributes, NO_STORY if name == "article" else HINTS)
                holders += 1
                stack.append((name, away, story, holders))
                opened[name] = opened.get(name, 0) + 1
    close()
    return out


def densities(b: Block) -> tuple[float, float, int]:
    """Share of the characters inside links, share of stop words, number of words."""
    words = WORD.findall(b.text.lower())
    return min(1.0, b.linked / len(b.text)), sum(w in STOP_WORDS for w in words) / max(len(words), 1), len(words)


def first_pass(b: Block, has_story: bool) -> int:
    """BAD, NEAR, GOOD or BRIEF for one block; has_story: the page has an article with blocks of its own."""
    links, stops, words = densities(b)
    moved = (IN_STORY if b.story else ELSEWHERE if has_story else 0) + (IN_AWAY if b.away else 0)
    if links > (LINKS_IN_STORY if moved > 0 else MOST_LINKS):
        if moved <= 0 or stops < FEW_STOPS:
            return BRIEF if moved > 0 and words <= LONE_LINK else BAD
    if len(b.text) < SHORT and (stops < FEW_STOPS or moved <= 0):
        return BRIEF if moved >= 0 and (moved > 0 or not b.linked) else BAD
    by_text = (GOOD if len(b.text) > LONG else NEAR) if stops >= MANY_STOPS else NEAR if stops >= FEW_STOPS else BAD
    return max(BAD, min(GOOD, by_text + moved))


def second_pass(blocks: list[Block], labels: list[int], has_story: bool) -> list[bool]:
    """Whether each block is kept.

    NEAR and BRIEF blocks look for the nearest decided block on either side: in their article; without one, under the same holder, and
    else on the page.  NEAR ones need one good neighbour.  BRIEF ones take the label that both have; between two labels they are
    kept in an article or if the good one is under the same holder.  An article's two ends count as good, a page's as bad.
    """
    n = len(blocks)
    beside: list[list[tuple[int, int]]] = [[], []]  # for either side and block: label, holder
    for order, side in ((range(n), beside[0]), (range(n - 1, -1, -1), beside[1])):
        page, story, holder = (BAD, -1), {}, {}
        for i in order:
            b = blocks[i]
            outer = has_story and not b.story
            side.append(story.get(b.story, (GOOD, b.holder)) if b.story else holder.get(b.holder, (BAD, -1) if outer else page))
            if labels[i] in (GOOD, BAD) and not (b.story and b.away):
                page = (labels[i], b.holder)
                if b.story:
                    story[b.story] = page
                holder[b.holder] = page
    beside[1].reverse()
    kept = []
    for b, label, x, y in zip(blocks, labels, *beside, strict=True):
        good = [side for side in (x, y) if side[0] == GOOD]
        mixed = len(good) == 1 and (bool(b.story) or good[0][1] == b.holder)
        kept.append(label == GOOD or label == NEAR and bool(good) or label == BRIEF and (len(good) == 2 or mixed))
    return kept


def main_text(page: str | None) -> str:
    """The article: its blocks in page order, joined by one line end; empty if there is none."""
    blocks = blocks_of(page or "")
    has_story = any(b.story and not b.away for b in blocks)
    labels = [first_pass(b, has_story) for b in blocks]
    return "\n".join(b.text for b, ok in zip(blocks, second_pass(blocks, labels, has_story), strict=True) if ok)


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """id, url, text for every row of pages; null pages are empty and have an empty text, rows repeated are repeated."""
    kind = pages.select(id_col).schema[0].dataType.simpleString()

    def run(batches):
        for whole in batches:
            for at in range(0, whole.num_rows, 200):
                batch = whole.slice(at, 200)
                texts = [main_text(x) for x in batch.column("html").to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("url"), pa.array(texts, pa.string())], ["id", "url", "text"])

    rows = pages.selectExpr(f"`{id_col}` as id", f"cast(`{url_col}` as string) as url", f"cast(`{html_col}` as string) as html")
    return rows.mapInArrow(run, f"id {kind}, url string, text string").withColumnRenamed("id", id_col)
