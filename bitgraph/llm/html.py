"""Main text of web pages by two-pass block rules.

A page is cut into blocks at block-level tags. The first pass decides blocks by where they stand (menus, forms, page
headers and the like are out), by link density, by stop-word density and by length; blocks of few words stay undecided.
In the second pass these inherit from the nearest decided blocks before and behind, in the same article where there is
one: alike neighbours decide, else the nearer one. What is left undecided is in if it stands in an article.

Defined results: null or empty html gives an empty text; markup cut off anywhere is read as far as it goes; repeated rows
get equal results; an empty table gives an empty result; other columns pass through unless named like a result. Nothing
is dropped for its length.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Elements without text of their own, and where a block begins and ends.
RAW = "script style noscript template iframe textarea select svg math object title datalist canvas audio video head".split()
BLOCK = """address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form
h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody tfoot thead tr ul button""".split()
#: Elements that are never main text, and hints of such in class, id and role.
OUT = "nav footer aside form button dialog fieldset menu".split()
HINTS = """ad ads advert adverts advertisement advertising banner sponsor sponsored promo promotion menu nav navbar navigation breadcrumb breadcrumbs
sidebar footer masthead cookie cookies consent notice notices comment comments disqus respond reply replies share sharing social related
recommended recommendations newsletter subscribe subscription signup popup modal widget widgets toolbar pagination pager copyright legal
complementary contentinfo search dialog alert skip""".split()
#: Frequent words of English, German, French and Spanish.
STOP = frozenset("""the of and to in a is that it for on was with as be by this are from at or not have an they which you were his her their
der die das und ist nicht ein eine zu den von mit sich auf für im dem des auch es an werden aus er hat dass sie nach wird bei
le la les de des et est un une en que qui dans pour pas sur au par plus ce avec sont du il elle ne se
el los las y una por con para como más su al lo no del se es son pero sus le ha""".split())

LINKED = 0.5
#: Characters from which a block counts as long, and shares of stop words.
LONG = 200
SHORT_WORDS = 8
STOP_LOW, STOP_HIGH = 0.1, 0.25

TOKEN = re.compile(rf"""<!--.*?(?:--\s*>|\Z)|<(?P<raw>{"|".join(RAW)})\b(?P<rawattr>(?:[^<>"']|"[^"<]*"|'[^'<]*')*+)>|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attr>(?:[^<>"']|"[^"]*"|'[^']*')*+)>|<[/!?][^>]*(?:>|\Z)|<[a-zA-Z][^<>]*(?:>|\Z)|(?P<text>[^<]+|<)""", re.DOTALL | re.IGNORECASE)
CLOSE = {t: re.compile(rf"</{t}\s*>", re.IGNORECASE) for t in RAW}
NAMED = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.IGNORECASE)
HIDDEN = re.compile(r"""(?:^|\s)hidden(?:\s|=|/|$)|aria-hidden\s*=\s*["']?true|display\s*:\s*none""", re.IGNORECASE)
PARTS = re.compile(r"[a-z]+")
#: Letters of scripts that are written without spaces, and Latin letters.
UNSPACED = re.compile("[\u0e00-\u0eff\u1000-\u109f\u1780-\u17ff\u3040-\u30ff\u3400-\u9fff\uf900-\ufaff\U00020000-\U0003ffff]")
LATIN = re.compile("[A-Za-z\u00aa\u00ba\u00c0-\u024f\u1e00-\u1eff]")
NOT_LETTERS = re.compile(r"[\W\d_]+")
_BLOCK, _OUT, _HINTS = frozenset(BLOCK), frozenset(OUT), frozenset(HINTS)
VOID = frozenset("hr br".split())


@dataclass
class Block:
    text: str
    link_chars: int
    out: bool
    article: int
    good: bool | None = None


def is_out(tag: str, attr: str, in_article: bool) -> bool:
    if tag in _OUT or tag == "header" and not in_article:
        return True
    if not attr or tag in ("body", "html", "article", "main") and "comment" not in attr.lower():
        return False
    if HIDDEN.search(attr):
        return True
    names = " ".join("".join(x) for x in NAMED.findall(attr)).lower()
    return bool(names) and not _HINTS.isdisjoint(PARTS.findall(names))


def blocks_of(page: str) -> list[Block]:
    """The blocks with text, in page order. ``article`` numbers the innermost article or main they stand in, 0 for none."""
    out: list[Block] = []
    open_tags: list[tuple[str, bool, int]] = []
    text: list[str] = []
    links, linked, n_articles, at = 0, 0, 0, 0

    def flush() -> None:
        nonlocal linked
        if text:
            joined = " ".join(entities.unescape("".join(text)).split())
            if joined:
                top = open_tags[-1] if open_tags else ("", False, 0)
                out.append(Block(joined, linked, top[1], top[2]))
            text.clear()
        linked = 0

    while m := TOKEN.match(page, at):
        at = m.end()
        if (t := m["text"]) is not None:
            text.append(t)
            linked += len(t.strip()) if links else 0
        elif raw := m["raw"]:
            raw = raw.lower()
            end = CLOSE[raw].search(page, at)
            if raw == "head" or m["rawattr"].endswith("/"):
                continue  # its title, styles and scripts are raw themselves
            at = end.end() if end else len(page)
        elif tag := m["tag"]:
            tag = tag.lower()
            if tag == "a":
                links = 0 if m["end"] else 1
            elif tag in ("br", "td", "th"):
                text.append(" ")
            if tag not in _BLOCK:
                continue
            flush()
            if tag in VOID:
                continue
            if m["end"]:
                if any(x[0] == tag for x in open_tags):
                    while open_tags.pop()[0] != tag:
                        pass
                continue
            links = 0
            if open_tags and open_tags[-1][0] in ("p", "h1", "h2", "h3", "h4", "h5", "h6"):
                open_tags.pop()  # these end where another block begins
            if tag in ("li", "dt", "dd", "tr", "option") and open_tags and open_tags[-1][0] == tag:
                open_tags.pop()
            above = open_tags[-1] if open_tags else ("", False, 0)
            article = above[2]
            if tag in ("article", "main"):
                n_articles += 1
                article = n_articles
            open_tags.append((tag, above[1] or is_out(tag, m["attr"] or "", bool(above[2])), article))
    flush()
    return out


def n_words(text: str) -> int:
    """Words of a text; of scripts without spaces, two characters count as one."""
    return max(len(text.split()), len(UNSPACED.findall(text)) // 2)


def stop_share(text: str) -> float:
    words = [NOT_LETTERS.sub("", w) for w in text.lower().split()]
    return sum(w in STOP for w in words) / max(1, len(words))


def is_long(b: Block) -> bool:
    """Whether a block's own words can decide."""
    return not b.out and b.link_chars <= LINKED * len(b.text) and not b.text.startswith("©") and n_words(b.text) >= SHORT_WORDS


def of_other_script(text: str) -> bool:
    letters = sum(map(str.isalpha, text))
    return 2 * len(LATIN.findall(text)) < letters


def in_known_language(blocks: list[Block]) -> bool:
    """Whether most words of the page's long blocks are in blocks that show the known stop words."""
    long = [(n_words(b.text), stop_share(b.text) >= STOP_LOW) for b in blocks if is_long(b)]
    return 2 * sum(n for n, known in long if known) >= sum(n for n, _ in long)


def first_pass(b: Block, known: bool = True) -> bool | None:
    """``known``: the page is in a language whose stop words are listed. In any other one, length and links decide."""
    if b.out or b.link_chars > LINKED * len(b.text):
        return False
    if not is_long(b):
        return None
    if not known or of_other_script(b.text):
        return True
    stop = stop_share(b.text)
    if stop >= STOP_HIGH or stop >= STOP_LOW and len(b.text) >= LONG:
        return True
    return None if b.article or stop >= STOP_LOW else False


def second_pass(blocks: list[Block]) -> None:
    """Undecided blocks inherit from the nearest decided ones of their article; those of the page stand at its edges."""
    n = len(blocks)
    last: dict[int, tuple[int, bool]] = {}
    before: list[tuple[int, bool] | None] = [None] * n
    for i, b in enumerate(blocks):
        before[i] = last.get(b.article)
        if b.good is not None and not (b.article and b.out):
            last[b.article] = (i, b.good)
    last.clear()
    verdicts: list[tuple[int, bool]] = []
    for i in range(n - 1, -1, -1):
        b = blocks[i]
        behind, ahead = before[i], last.get(b.article)
        if b.good is not None:
            if not (b.article and b.out):
                last[b.article] = (i, b.good)
            continue
        near = [x for x in (behind, ahead) if x]
        if b.article and not any(good for _, good in near):
            verdicts.append((i, True))  # an article of short blocks only, or with a list of links in it
        elif not near or len(near) == 1 and not b.article:
            verdicts.append((i, False))
        else:
            verdicts.append((i, min(near, key=lambda x: (abs(x[0] - i), not x[1]))[1]))
    for i, good in verdicts:
        blocks[i].good = good


def extract(page: str | None) -> str:
    blocks = blocks_of(page or "")
    known = in_known_language(blocks)
    for b in blocks:
        b.good = first_pass(b, known)
    second_pass(blocks)
    return "\n".join(b.text for b in blocks if b.good)


def main_text(pages: DataFrame, html: str = "html") -> DataFrame:
    """pages without the html, with text and n_chars."""
    new = [T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())]
    passed = [f for f in pages.schema if f.name not in ("text", "n_chars", html)]

    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            texts = [extract(h) for h in batch.column(len(passed)).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns[: len(passed)], pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=[f.name for f in [*passed, *new]])

    return pages.withColumn("__html", pages[html]).select(*[f.name for f in passed], "__html").mapInArrow(batches, T.StructType([*passed, *new]))
