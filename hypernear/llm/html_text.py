"""Main text of web pages: host suffix arrays over the pages' token streams, held against the markup.

Pages are cut into blocks and tokens. In the suffix array of a host's token streams (a separator of its own after each page), a run of at least
``least_run`` tokens that occurs on two or more pages of different tokens covers its tokens; blocks that are mostly covered are
boilerplate and go, unique ones stay. ``extract`` does this for the pages of one host in memory. A token is covered just if it lies in a
repeated window of ``least_run`` tokens, so for whole tables ``main_text`` needs only the array's buckets to that depth: windows are hashed with their
host, and the least and the greatest content that has a window are kept, which sums up by task before any shuffle. Each host is judged
whole, and never gathered.

What is left is held against the markup: blocks in menus, headers, footers, sidebars, notices, adverts, forms, reader comments
and hidden elements go too, as a page alone on its host repeats nothing. Text marked as an article (or, without one, as
main content) is kept whole: a passage that two articles of a host share is content, which repetition alone would remove (see README for how
much). On a page with such marks the markup alone decides, and repetition changes nothing; ``hints=False`` leaves all to repetition.

Defined cases: null html is empty and gives an empty text; a null or odd url has host ''; repeated rows are extracted each
(and count as one page when runs are counted, as do all pages with the same tokens); an empty table gives an empty result; unclosed,
stray and misnested tags are tolerated; other columns are dropped.
"""

from __future__ import annotations

import html as entities
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, persisted
from .order_minhash import MIX, WordHashes, mix

# Element names by role.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea title iframe object svg canvas audio video select".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr img".split())
ASIDE = frozenset("nav footer aside form head menu dialog button fieldset search".split())
CLOSES_P = frozenset("address article aside blockquote details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split())
SAME = {"li": "li", "dt": "dt dd", "dd": "dt dd", "tr": "tr td th", "td": "td th", "th": "td th", "option": "option"}
STOP = frozenset("ul ol dl table article section div main body".split())
UNWANTED = re.compile(r"(?:^|[\s_-])(?:ads?|ad(?:box|unit|slot|block)s?|advert\w*|adsense|sponsor\w*|promo\w*|banner|cookie\w*|consent|gdpr|notices?|popup|modal|overlay|sidebar\w*|side|menu\w*|nav\w*|breadcrumb\w*|footer\w*|toolbar|comments?|commentlist|respond|reply|replies|disqus\w*|share|sharing|social\w*|related|recommend\w*|newsletter|subscribe\w*|signup|login|widget\w*|pagination|pager|skip|alert|form|search)(?=$|[\s_-])", re.I)
HEADER = re.compile(r"(?:^|[\s_-])(?:header|masthead|topbar)(?=$|[\s_-])", re.I)
CONTENT = re.compile(r"(?:^|\s)(?:article|post|entry|story|content|main)(?:[_-](?:body|content|text|main))?(?=$|\s)|articleBody", re.I)
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
TOKENS = re.compile(r"""<!--.*?(?:-->|$)|<![^>]*>?|<\?[^>]*>?|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']|"[^"]*"|'[^']*'|["'])*?)>|([^<]+|<)""", re.S)
ATTRIBUTE = re.compile(r"""([a-zA-Z-]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")


def unwanted(name: str, attributes: str, level: int) -> bool:
    """Whether the markup calls an element a menu, header, footer, sidebar, notice, advert, form or comment. A header within
    marked content belongs to it."""
    if name in ASIDE or (name == "header" and not level):
        return True
    if not attributes or name in ("html", "body", "main"):
        return False
    for key, *values in ATTRIBUTE.findall(attributes):
        key, value = key.lower(), max(values, key=len)
        if key in ("class", "id") and (UNWANTED.search(value) or (not level and HEADER.search(value))):
            return True
        if key == "role" and value.strip().lower() in ROLES or key == "hidden" or (key == "aria-hidden" and value.lower() == "true") or (key == "style" and re.search(r"display\s*:\s*none", value, re.I)):
            return True
    return False


def content_level(name: str, attributes: str) -> int:
    """2 for an article, 1 for an element that is named as the main content, else 0."""
    if name == "article":
        return 2
    if name == "main":
        return 1
    for key, *values in ATTRIBUTE.findall(attributes):
        key, value = key.lower(), max(values, key=len)
        if key in ("class", "id", "itemprop") and CONTENT.search(value) or key == "role" and value.lower() in ("main", "article"):
            return 1
    return 0


def blocks(html: str | None) -> list[tuple[str, int, bool]]:
    """Text blocks in page order as (text, level of the content they stand in, unwanted by markup)."""
    made: list[tuple[str, int, bool]] = []
    stack: list[tuple[str, int, bool]] = []  # name, level, unwanted
    pieces: list[str] = []
    state = (0, False)
    skip = ""

    def flush() -> None:
        text = " ".join(entities.unescape("".join(pieces)).split())
        pieces.clear()
        if text:
            made.append((text, *state))

    def close(names: str) -> None:
        """Pop the innermost open element of these names, unless a container stands before it."""
        wanted = names.split()
        for at in range(len(stack) - 1, -1, -1):
            if stack[at][0] in wanted:
                del stack[at:]
                return
            if stack[at][0] in STOP:
                return

    for found in TOKENS.finditer(html or ""):
        end, name, attributes, text = found.groups()
        if text is not None:
            if not skip:
                pieces.append(text)
            continue
        if name is None:
            continue
        name = name.lower()
        if skip:
            if end and name == skip:
                skip = ""
            continue
        if name not in INLINE:
            flush()
        if end:
            for at in range(len(stack) - 1, -1, -1):
                if stack[at][0] == name:
                    if name in INLINE and any(n not in INLINE for n, *_ in stack[at + 1 :]):
                        break  # a stray inline end tag must not close blocks
                    del stack[at:]
                    break
        elif name in RAW:
            if not attributes.rstrip().endswith("/"):
                skip = name
            continue
        elif name not in VOID:
            if name in CLOSES_P:
                close("p")
            if name in SAME:
                close(SAME[name])
            level, gone = (stack[-1][1], stack[-1][2]) if stack else (0, False)
            gone = gone or unwanted(name, attributes, level)
            if not gone and level < 2 and (attributes or name in ("article", "main")):
                level = max(level, content_level(name, attributes))
            stack.append((name, level, gone))
        new = (stack[-1][1], stack[-1][2]) if stack else (0, False)
        if new != state:
            flush()
            state = new
    flush()
    return made


def suffix_array(flat: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes of a token stream in order, and how many tokens each shares with the one before it.

    Ranks by the first k tokens, paired k apart, rank by the first 2k; kept by level, they also measure shared prefixes, longest step first.
    """
    n = len(flat)
    ranks, depth = [np.unique(flat, return_inverse=True)[1].astype(np.int64)], 1
    while n and depth < n and ranks[-1].max() < n - 1:
        later = np.concatenate([ranks[-1][depth:], np.full(min(depth, n), -1, dtype=np.int64)])[:n]
        ranks.append(np.unique(ranks[-1] * (n + 1) + later + 1, return_inverse=True)[1].astype(np.int64))
        depth *= 2
    order = np.argsort(ranks[-1], kind="stable") if n else np.empty(0, dtype=np.int64)
    shared = np.zeros(n, dtype=np.int64)
    if n > 1:
        a, b = order[:-1].copy(), order[1:].copy()
        for level in range(len(ranks) - 1, -1, -1):
            padded = np.append(ranks[level], [-1])
            same = (a < n) & (b < n) & (padded[np.minimum(a, n)] == padded[np.minimum(b, n)])
            step = np.where(same, 1 << level, 0)
            shared[1:] += step
            a, b = a + step, b + step
    return order, shared


def covered(streams: list[list[str]], least_run: int) -> list[np.ndarray]:
    """Per page, which of its tokens lie in a run of at least least_run tokens that another page has too: in the suffix array of all pages
    (a separator of its own after each), a suffix shares its longest run with the nearest suffix of another page, before or after it."""
    ids: dict[str, int] = {}
    tokens = [[ids.setdefault(t, len(ids)) for t in page] for page in streams]
    flat = np.array([t for k, page in enumerate(tokens) for t in (*page, len(ids) + k)], dtype=np.int64)
    owner = np.repeat(np.arange(len(tokens)), [len(p) + 1 for p in tokens])
    order, shared = suffix_array(flat)
    whose = owner[order]
    edges = np.flatnonzero(np.append(whose[1:] != whose[:-1], True)) + 1 if len(order) else []
    longest, begun = np.zeros(len(flat), dtype=np.int64), 0
    for end in edges:  # of suffixes of one page that stand together, the shared prefix with what stands before and after them
        before = np.minimum.accumulate(shared[begun:end]) if begun else np.zeros(end - begun, dtype=np.int64)
        after = np.minimum.accumulate(np.append(shared[begun + 1 : end], shared[end])[::-1])[::-1] if end < len(order) else np.zeros(end - begun, dtype=np.int64)
        longest[order[begun:end]] = np.maximum(before, after)
        begun = end
    cover = np.zeros(len(flat) + 1, dtype=np.int64)
    starts = np.flatnonzero(longest >= least_run)
    np.add.at(cover, starts, 1)
    np.add.at(cover, starts + longest[starts], -1)
    hit = np.cumsum(cover)[: len(flat)] > 0
    bounds = np.cumsum([0] + [len(p) + 1 for p in tokens])
    return [hit[a : b - 1] for a, b in zip(bounds[:-1], bounds[1:])]


def unhinted(page: list[tuple[str, int, bool]]) -> list[tuple[str, int, bool]]:
    """Blocks as if markup said nothing of what they are."""
    return [(text, 0, False) for text, _, _ in page]


def extract(pages: list[str | None], least_run: int = 6, share: float = 0.8, hints: bool = True) -> list[str]:
    """Main texts of the pages of one host, by its suffix array in memory."""
    parsed = [blocks(p) if hints else unhinted(blocks(p)) for p in pages]
    outer = [[b for b in page if not b[1]] for page in parsed]
    streams = [[[t.lower() for t in WORD.findall(b[0])] for b in page] for page in outer]
    flat = [tuple(t for b in page for t in b) for page in streams]
    different = list(dict.fromkeys(flat))  # pages of the same tokens are one page: copies and mirrors don't cover each other
    hit_of = dict(zip(different, covered(different, least_run)))
    hits = [hit_of[page] for page in flat]
    return [kept(page, mine, hit, share) for page, mine, hit in zip(parsed, streams, hits)]


def level_of(page: list[tuple[str, int, bool]]) -> int:
    """The highest level of content that markup leaves on a page; only at 0 does repetition decide."""
    return max((level for _, level, gone in page if not gone), default=0)


def kept(page: list[tuple[str, int, bool]], mine: list[list[str]], hit: np.ndarray, share: float) -> str:
    """Main text of a page of blocks: mine are the tokens of those outside marked content, hit says which of them are covered."""
    bounds = np.cumsum([0] + [len(b) for b in mine])
    boiler = [len(b) > 0 and hit[a : a + len(b)].sum() >= share * len(b) for a, b in zip(bounds, mine)]
    marked, at, texts = level_of(page), 0, []
    for text, level, gone in page:
        repeated = False
        if not level:
            repeated = boiler[at]
            at += 1
        if not gone and not repeated and level == marked:
            texts.append(text)
    return " ".join(texts)


def outer_tokens(page: list[tuple[str, int, bool]]) -> list[list[str]]:
    """Tokens of the blocks outside marked content."""
    return [[t.lower() for t in WORD.findall(text)] for text, level, _ in page if not level]


def windows(mine: list[list[str]], host: str, least_run: int, memo: WordHashes) -> tuple[np.ndarray, np.ndarray]:
    """A hash of the host and each run of least_run tokens, in page order, and a hash of all tokens (one value)."""
    hashes = np.fromiter((memo[t] for b in mine for t in b), dtype=np.uint64)
    n = max(0, len(hashes) - least_run + 1)
    total = np.full(n, memo[host], dtype=np.uint64)
    for k in range(least_run):
        total = mix(total + MIX) ^ hashes[k : k + n]
    places = mix(np.arange(1, len(hashes) + 1, dtype=np.uint64) * MIX)
    owner = mix(mix(hashes ^ places).sum(dtype=np.uint64, keepdims=True))
    return mix(total).view(np.int64), owner.view(np.int64)


def host_of(url: Column) -> Column:
    """After the first ://, up to /, ?, # or the end, with A-Z lower-cased; '' where there is none."""
    host = F.regexp_extract(after_scheme(url), r"^[^/?#]*", 0)
    lower = F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    return F.when(F.instr(url, "://") > 0, lower).otherwise("")


def after_scheme(url: Column) -> Column:
    return F.substring(url, F.instr(url, "://") + 3, F.length(url))


def main_text(pages: DataFrame, least_run: int = 6, share: float = 0.8, hints: bool = True) -> DataFrame:
    """page_id, url, text and n_chars of every page. Without ``hints`` repetition alone decides, whatever the markup says."""
    host = F.coalesce(host_of(F.col("url")), F.lit("")).alias("host")
    keyed = pages.select("page_id", "url", "html", host, F.unhex(F.md5(F.concat_ws(" ", host, "html"))).alias("key"))

    def parsed(html: str | None) -> list[tuple[str, int, bool]]:
        return blocks(html) if hints else unhinted(blocks(html))

    def found(batches):
        """Windows of every page with its content."""
        memo = WordHashes()
        for batch in batches:
            runs, owners = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for name, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                made, owner = windows(outer_tokens(parsed(html)), name, least_run, memo)
                runs.append(np.unique(made))
                owners.append(np.repeat(owner, len(runs[-1])))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(runs)), pa.array(np.concatenate(owners))], names=["run", "owner"])

    def asked(batches):
        """Windows of the pages on which repetition decides."""
        memo = WordHashes()
        for batch in batches:
            keys, runs = [], [np.zeros(0, np.int64)]
            for name, html, key in zip(*(batch.column(k).to_pylist() for k in range(3))):
                page = parsed(html)
                if not level_of(page):
                    runs.append(np.unique(windows(outer_tokens(page), name, least_run, memo)[0]))
                    keys += [key] * len(runs[-1])
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(np.concatenate(runs))], names=["of", "run"])

    def run(batches):
        memo = WordHashes()
        for batch in batches:
            texts = []
            for name, html, repeated in zip(*(batch.column(k).to_pylist() for k in (2, 3, 4))):
                page = parsed(html)
                mine = outer_tokens(page)
                hit = np.zeros(sum(map(len, mine)), dtype=bool)
                if repeated:
                    starts = np.flatnonzero(np.isin(windows(mine, name, least_run, memo)[0], np.array(repeated, dtype=np.int64)))
                    for k in range(least_run):
                        hit[starts + k] = True
                texts.append(kept(page, mine, hit, share))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    ends = keyed.select("host", "html").mapInArrow(found, "run long, owner long").groupBy("run").agg(F.min("owner").alias("low"), F.max("owner").alias("high"))
    shared = persisted(ends.filter("low <> high").select("run"), "repeated-runs")
    wanted = keyed.select("host", "html", "key").mapInArrow(asked, "of binary, run long").join(shared, "run")
    # A table of measured size: Spark broadcasts it while it is small, and no page moves for it.
    held = persisted(wanted.groupBy("of").agg(F.collect_set("run").alias("repeated")), "pages-with-repeats")
    met = keyed.join(held, F.col("key") == F.col("of"), "left").select("page_id", "url", "host", "html", "repeated")
    return met.mapInArrow(run, "page_id long, url string, text string, n_chars long")
