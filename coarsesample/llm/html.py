"""Main text of web pages, with boilerplate found by a suffix array over each host's pages.

A page is parsed into blocks. Blocks in menus, headers, footers, sidebars, forms, adverts, notices and
comments, known by element, role, class or id, are not its text; if it has an ``article`` or ``main``,
neither is what lies outside. That markup is only the prior: what is left of all pages, containers
included, goes through the array.

The token streams of a host's distinct pages are put together, every block closed by a symbol of its
own, and their suffix array is built by prefix doubling. Neighbours in it that agree in ``run`` symbols
or more form classes; where a class has suffixes of enough distinct pages, its tokens are a repeated
run, and runs that overlap join to repeats of any length. Blocks shorter than ``run`` count as a whole.
Repeated tokens are removed and unique runs stay. Enough is ``share`` of the pages and ``fewest`` of
them where no container vouches for a text, and ``main_share`` and ``main_fewest`` where one does:
articles quote each other, and the extraction may drop nothing but boilerplate. A page is known by its
blocks, so copies of it under other ids or addresses count once.

An array takes pages of about ``group_bytes`` of html at most. A host beyond that is cut into slices
by a hash of the pages' blocks, each with an array of its own, and counts of a run in all slices are
added, so that the result is that of one array over the whole host. A run that reaches a share of the
host's pages reaches it in some slice at least, so a slice reports those runs only. Where some slices
have not reported a run that could still be repeated, it is counted in all of them.

Pages are parsed where they lie, and one shuffle takes their blocks to the arrays, once for copies in
the same task. Repeated runs go to the pages of their hosts alone; hosts without any need no shuffle.

Defined results: null or empty html gives an empty text; broken or unclosed markup is closed at the
end of its parent; pages of equal blocks are one page to the array and each get their result; null
urls share one host; an empty table gives an empty result. Only page_id, url and html are read.
"""

from __future__ import annotations

import hashlib
import html
import math
import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coarsesample.runtime import broadcast_if_small, materialize

# Elements of HTML by their part in a page.
RAW = "script style noscript template textarea iframe svg math canvas object select"
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
INLINE = set("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q ruby rb rp rt s samp small span strike strong sub sup time tt u var wbr".split())
BOILER_TAGS = set("nav header footer aside form head menu dialog button noscript title".split())
MAIN_TAGS = {"article", "main"}
BOILER_ROLES = set("navigation banner contentinfo complementary search menu menubar dialog alert form".split())
# Names in class and id that mark what is no article.
BOILER_NAMES = set(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription signup sidebar widget widgets menu submenu navbar nav navigation breadcrumb breadcrumbs footer masthead share sharing social related recommended recommendations comment comments commentlist respond disqus pagination pager toolbar skip login search searchbox copyright disclaimer".split()
)
NEUTRAL_NAMES = set("area bar block body box button buttons container content form head inner item items link links list main nav outer panel row section site text title top wrap wrapper".split())
BOILER_PHRASES = set("header site-header page-header top-bar topbar main-nav site-nav side-bar".split())

_MARK = re.compile(
    r"<!--.*?(?:-->|\Z)|<(?P<raw>" + RAW.replace(" ", "|") + r")\b(?:\"[^\"]*\"|'[^']*'|[^>\"'])*(?:/>|>.*?(?:</(?P=raw)\s*>|\Z))"
    r"|<(?P<end>/?)(?P<name>[a-zA-Z][^\s/>]*)(?P<attrs>(?:\"[^\"]*\"|'[^']*'|[^>\"'])*)>|<(?P<end2>/?)(?P<name2>[a-zA-Z][^\s/>]*)(?P<attrs2>[^>]*)>|<[!?/][^>]*>",
    re.S | re.I,
)
_ATTR = re.compile(r"([a-zA-Z_:-]+)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+)")
_HIDDEN = re.compile(r"(?:^|\s)hidden(?:\s|=|/|$)", re.I)
_HOST = r"^\s*(?:[a-zA-Z][\w+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)"

MAIN, OUTSIDE, BOILER = 0, 1, 2


def _named(label: str) -> bool:
    """Whether a class or id says boilerplate: its parts are such names, or add nothing to them."""
    if label in BOILER_PHRASES:
        return True
    rest = set(re.split(r"[-_]+", label)) - NEUTRAL_NAMES
    return bool(rest) and rest <= BOILER_NAMES


def _zone(name: str, attrs: str, inside: bool) -> int:
    """What an element says of the text in it; ``inside`` a container, headers head the article and paragraphs are its text."""
    if name in BOILER_TAGS and not (inside and name == "header"):
        return BOILER
    if attrs and ("=" in attrs or "hidden" in attrs.lower()):
        if _HIDDEN.search(attrs):
            return BOILER
        found = {k.lower(): v.strip("\"'").lower() for k, v in _ATTR.findall(attrs)}
        if found.get("role") in BOILER_ROLES or found.get("aria-hidden") == "true" or "display:none" in found.get("style", "").replace(" ", ""):
            return BOILER
        if name not in MAIN_TAGS and name not in ("body", "html") and not (inside and name == "p"):
            if any(map(_named, f"{found.get('class', '')} {found.get('id', '')}".split())):
                return BOILER
        if found.get("role") == "main":
            return MAIN
    return MAIN if name in MAIN_TAGS else OUTSIDE


def parse(page: str | None) -> tuple[bool, list[tuple[int, list[str]]]]:
    """Whether the page has a container, and its blocks in order, each with its zone and tokens."""
    page = page or ""
    stack: list[tuple[str, int]] = []
    open_names: Counter = Counter()
    inside, boiler, has_main = 0, 0, False
    blocks: list[tuple[int, list[str]]] = []
    text: list[str] = []

    def flush() -> None:
        if text:
            tokens = html.unescape("".join(text)).split()
            text.clear()
            if tokens:
                blocks.append((BOILER if boiler else MAIN if inside else OUTSIDE, tokens))

    def pop() -> None:
        nonlocal inside, boiler
        name, zone = stack.pop()
        open_names[name] -= 1
        inside -= zone == MAIN
        boiler -= zone == BOILER

    at = 0
    for m in _MARK.finditer(page):
        if m.start() > at:
            text.append(page[at : m.start()])
        at = m.end()
        name = (m["name"] or m["name2"] or "").lower()
        if not name:
            if m["raw"]:
                text.append(" ")
            continue
        ends = m["end"] or m["end2"]
        if name in VOID:
            if name in ("br", "hr", "img"):
                text.append(" ")
            continue
        if ends:
            if open_names[name]:
                flush() if name not in INLINE or stack[-1][1] != OUTSIDE else None
                while stack[-1][0] != name:
                    flush()
                    pop()
                flush() if stack[-1][1] != OUTSIDE else None
                pop()
            elif name not in INLINE:
                flush()
            continue
        attrs = m["attrs"] if m["attrs"] is not None else (m["attrs2"] or "")
        zone = _zone(name, attrs, inside > 0)
        if name in INLINE and zone == OUTSIDE:
            continue
        if name == "body":
            flush()
            while open_names["head"]:
                pop()
        flush()
        if attrs.endswith("/") and name not in MAIN_TAGS:
            continue
        stack.append((name, zone))
        open_names[name] += 1
        inside += zone == MAIN
        boiler += zone == BOILER
        has_main |= zone == MAIN and not boiler
    if at < len(page):
        text.append(page[at:])
    flush()
    return has_main, blocks


def candidates(page: str | None) -> tuple[bool, list[list[str]]]:
    """What the markup leaves of a page: the blocks of its containers, or else those that nothing marks."""
    has_main, blocks = parse(page)
    return has_main, [tokens for zone, tokens in blocks if zone == (MAIN if has_main else OUTSIDE)]


def suffix_array(symbols: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts of all suffixes in order, and how many symbols each shares with the one before.

    Prefix doubling: ranks by 2h symbols come from the ranks by h at a place and h further on. The
    ranks of all rounds then give the common prefixes, longest rounds first.
    """
    n = len(symbols)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    rank, reach = np.unique(symbols, return_inverse=True)[1].astype(np.int64), 1
    rounds = [rank.astype(np.int32)]
    order = np.argsort(rank, kind="stable")
    while reach < n and rank[order[-1]] < n - 1:
        after = np.zeros(n, np.int64)
        after[:-reach] = rank[reach:] + 1
        key = rank * (n + 1) + after
        order = np.argsort(key, kind="stable")
        change = np.diff(key[order]) != 0
        rank = np.empty(n, np.int64)
        rank[order] = np.append(0, np.cumsum(change))
        rounds.append(rank.astype(np.int32))
        reach *= 2
    shared = np.zeros(n, np.int64)
    a, b = order[:-1], order[1:]
    for level in range(len(rounds) - 1, -1, -1):
        x, y = a + shared[1:], b + shared[1:]
        inside = (x < n) & (y < n)
        same = inside & (rounds[level][np.minimum(x, n - 1)] == rounds[level][np.minimum(y, n - 1)])
        shared[1:] += same * (1 << level)
    return order, shared


def pages_sharing(symbols: np.ndarray, page: np.ndarray, run: int) -> np.ndarray:
    """For each place, the distinct pages that hold the ``run`` symbols from there."""
    order, shared = suffix_array(symbols)
    kind = np.cumsum(shared < run)
    pages = int(page.max()) + 1 if len(page) else 1
    held = np.unique(kind * pages + page[order]) // pages
    out = np.zeros(len(symbols), np.int64)
    out[order] = np.bincount(held, minlength=int(kind[-1]) + 1 if len(kind) else 1)[kind]
    return out


def repeats(distinct: list[tuple], run: int, least: int) -> dict[str, int]:
    """Runs of ``run`` tokens, and whole shorter blocks, that ``least`` of the distinct pages hold, and how many do."""
    whole = Counter(b for _, blocks in distinct for b in {b for b in blocks if len(b) < run})
    out = {" ".join(b): n for b, n in whole.items() if n >= least}
    known: dict[str, int] = {}
    symbols, tokens, owner, ends = [], [], [], 0
    for i, (_, blocks) in enumerate(distinct):
        for b in blocks:
            if len(b) >= run:
                ends += 1
                symbols += [known.setdefault(t, len(known)) for t in b]
                symbols.append(-ends)
                tokens += [*b, ""]
                owner += [i] * (len(b) + 1)
    if symbols:
        held, ending = pages_sharing(np.array(symbols, np.int64), np.array(owner, np.int64), run), np.append(0, np.cumsum(np.array(symbols) < 0))
        starts = np.flatnonzero(held >= least)
        starts = starts[starts + run <= len(symbols)]
        for i in starts[ending[starts + run] == ending[starts]]:
            out[" ".join(tokens[i : i + run])] = int(held[i])
    return out


def runs_of(block: tuple | list, run: int) -> list[str]:
    """What repeats() may name of a block: its runs, or itself if it is shorter."""
    return [" ".join(block[i : i + run]) for i in range(max(1, len(block) - run + 1))]


def without(blocks: tuple | list, gone: set[str], run: int) -> str:
    """Text of blocks without the tokens of the runs in ``gone``."""
    kept: list[str] = []
    for b in blocks:
        step = np.zeros(len(b) + 1, int)
        for i, text in enumerate(runs_of(b, run)):
            if text in gone:
                step[i] += 1
                step[min(i + run, len(b))] -= 1
        covered = np.cumsum(step)[:-1] > 0
        kept += [t for t, c in zip(b, covered, strict=True) if not c] if covered.any() else b
    return " ".join(kept)


def unique_texts(pages: list[str | None], run: int, share: float, fewest: int, main_share: float, main_fewest: int) -> list[str]:
    """Texts of one array's pages, without the runs that enough of them repeat."""
    seat: dict[tuple, int] = {}
    at = []
    for page in pages:
        has_main, blocks = candidates(page)
        at.append(seat.setdefault((has_main, tuple(map(tuple, blocks))), len(seat)))
    distinct = list(seat)
    least = {m: max(main_fewest, math.ceil(main_share * len(distinct))) if m else max(fewest, math.ceil(share * len(distinct))) for m in {m for m, _ in distinct}}
    found = repeats(distinct, run, min(least.values(), default=1))
    gone = {m: {text for text, n in found.items() if n >= most} for m, most in least.items()}
    texts = [without(blocks, gone[m], run) for m, blocks in distinct]
    return [texts[i] for i in at]


def coded(page: str | None) -> str:
    """What the markup leaves of a page as one string: m with a container, else p, then a line a block."""
    has_main, blocks = candidates(page)
    return ("m" if has_main else "p") + "\n".join(map(" ".join, blocks))


def decoded(code: str) -> tuple[bool, tuple]:
    return code[0] == "m", tuple(tuple(b.split(" ")) for b in code[1:].split("\n") if b)


def extract(pages: DataFrame, run: int = 12, share: float = 0.5, fewest: int = 3, main_share: float = 0.8, main_fewest: int = 10, group_bytes: int = 2_000_000) -> DataFrame:
    """page_id, url, text, n_chars of every page."""
    given = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html", F.coalesce(F.lower(F.regexp_extract("url", _HOST, 1)), F.lit("")).alias("host"))
    weight = F.coalesce(F.octet_length("html"), F.lit(0)) + F.lit(256)
    sizes = given.groupBy("host").agg(F.sum(weight).alias("bytes"))
    large = broadcast_if_small(sizes.where(F.col("bytes") > group_bytes).select("host", F.ceil(F.col("bytes") / group_bytes).alias("slices")))
    slices = F.coalesce("slices", F.lit(1))

    def first_seen(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: set = set()
        for batch in batches:
            new = []
            for host, page in zip(batch["host"], batch["html"], strict=True):
                code = coded(page)
                key = host, hashlib.blake2b(code.encode(), digest_size=16).digest()
                if key not in seen:
                    seen.add(key)
                    new.append((host, code))
            yield pd.DataFrame(new, columns=["host", "code"])

    def reports(group: pd.DataFrame) -> pd.DataFrame:
        distinct = list(map(decoded, group["code"].unique()))
        n, mains = len(distinct), sum(m for m, _ in distinct)
        if group["slices"].iloc[0] > 1:
            least = max(1, math.ceil(min(share, main_share) * n - 1e-9))
        else:
            least = min([max(main_fewest, math.ceil(main_share * n))] * (mains > 0) + [max(fewest, math.ceil(share * n))] * (mains < n))
        found = repeats(distinct, run, least) if least <= n else {}
        head = [(None, n)] + list(found.items())
        out = pd.DataFrame({"item": [i for i, _ in head], "held": [h for _, h in head]})
        return out.assign(host=group["host"].iloc[0], slice=group["slice"].iloc[0], slices=group["slices"].iloc[0], n=n, mains=mains)

    def recount(group: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        wanted, held = set(asked["item"]), Counter()
        for code in group["code"].unique() if wanted else ():
            held.update({text for b in decoded(code)[1] for text in runs_of(b, run) if text in wanted})
        return pd.DataFrame([(group["host"].iloc[0], *x) for x in held.items()], columns=["host", "item", "held"])

    def removed(group: pd.DataFrame, found: pd.DataFrame) -> pd.DataFrame:
        gone = {m: set(found["item"][found["held"] >= found["main_least" if m else "least"]]) for m in (True, False)}
        texts = [without(blocks, gone[m], run) for m, blocks in map(decoded, group["code"])]
        return pd.DataFrame(list(zip(group["page_id"], group["url"], texts, strict=True)), columns=["page_id", "url", "text"])

    codes = given.select("host", "html").mapInPandas(first_seen, "host string, code string")
    dealt = codes.join(large, "host", "left").select("host", "code", slices.alias("slices")).withColumn("slice", F.pmod(F.xxhash64("code"), "slices"))
    found = materialize(dealt.groupBy("host", "slice").applyInPandas(reports, "host string, slice long, slices long, n long, mains long, item string, held long"), "repeats")

    each = found.where("item is null")
    least, main_least = (F.greatest(F.lit(f), F.ceil(F.lit(float(s)) * F.col("pages"))) for s, f in ((share, fewest), (main_share, main_fewest)))
    hosts = each.groupBy("host").agg(F.sum("n").alias("pages"), F.sum("mains").alias("mains"), F.count("n").alias("parts")).select("*", least.alias("least"), main_least.alias("main_least"))
    hosts = hosts.withColumn("lowest", F.least(F.when(F.col("mains") > 0, F.col("main_least")), F.when(F.col("mains") < F.col("pages"), F.col("least"))))
    known = found.where("item is not null").groupBy("host", "item").agg(F.sum("held").alias("held"), F.sum("n").alias("seen"), F.count("n").alias("reports")).join(hosts, "host")
    more = F.when(F.col("reports") < F.col("parts"), F.lit(float(min(share, main_share))) * (F.col("pages") - F.col("seen")) + 1e-6).otherwise(0.0)
    known = materialize(known.where(F.col("held") + more >= F.col("lowest")), "known")
    open_items = known.where("reports < parts").select("host", "item")
    final = known.select("host", "item", "held", "least", "main_least", "lowest")
    if open_items.limit(1).count():
        asked = open_items.join(each.select("host", "slice"), "host")
        own = dealt.join(broadcast_if_small(open_items.select("host").distinct()), "host", "left_semi")
        again = own.groupBy("host", "slice").cogroup(asked.groupBy("host", "slice")).applyInPandas(recount, "host string, item string, held long")
        exact = again.groupBy("host", "item").agg(F.sum("held").alias("exact"))
        final = final.join(exact, ["host", "item"], "left").withColumn("held", F.coalesce("exact", "held")).where("held >= lowest")
        final = materialize(final.drop("exact"), "repeated")

    @F.pandas_udf("string")
    def code(pages: pd.Series) -> pd.Series:
        return pd.Series([coded(page) for page in pages], dtype=object)

    all_pages = given.select("page_id", "url", "host", code("html").alias("code"))
    plain, text = all_pages, F.translate(F.substring("code", 2, 2**31 - 1), "\n", " ")
    out = None
    if final.limit(1).count():
        marked = broadcast_if_small(final.select("host").distinct())
        plain = all_pages.join(marked, "host", "left_anti")
        placed = all_pages.join(marked, "host", "left_semi").join(large, "host", "left").withColumn("slice", F.pmod(F.xxhash64("page_id", F.monotonically_increasing_id()), slices))
        lists = final.join(large, "host", "left").withColumn("slice", F.explode(F.sequence(F.lit(0).cast("long"), slices - 1)))
        given_back = placed.select(F.col("page_id").cast("string").alias("page_id"), "url", "host", "code", "slice").groupBy("host", "slice").cogroup(lists.groupBy("host", "slice"))
        out = given_back.applyInPandas(removed, "page_id string, url string, text string").select(F.col("page_id").cast("long").alias("page_id"), "url", "text")
    rest = plain.select("page_id", "url", text.alias("text"))
    return (rest if out is None else rest.unionByName(out)).select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
