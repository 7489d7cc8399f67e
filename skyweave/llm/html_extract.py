"""Main text of web pages by a suffix array over the token streams of a host.

A page is tokenised once into blocks; the outermost <article> or <main> is its main region. The blocks outside it, or all blocks of a page without one, join
the token stream of the page's host. The streams of a host's pages are concatenated with separators that occur once, a suffix array
with longest common prefixes finds the substrings of at least ``least`` tokens, or whole blocks, that occur in two distinct pages,
and covered tokens are boilerplate; unique runs stay, outside a main region as well. What the markup itself calls a
menu, header, footer, sidebar, notice, advert, form or comment is no main text, unique or not; inside a main region repeated passages are
the article's own and stay. A host of more than ``most_pages`` pages is dealt in shards: its runs of ``least`` tokens and its shorter
blocks are counted by 64-bit hash over all of its shards, and each shard gets back those that two distinct pages have, which
cover the same tokens as one array over the host.

Edge cases: null and empty pages have an empty text; pages without url share a host of their own; unclosed tags end with their
parents; stray < is text; repeated rows are separate pages but do not make each other boilerplate if they share a page_id;
extra columns are ignored."""

from __future__ import annotations

import html as _html
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import common as C

#: Elements by role (fixed lists).
BLOCKS = frozenset("address article aside blockquote body br caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead title tr ul".split())
RAW = frozenset("script style noscript template textarea iframe svg math canvas select object audio video".split())
NOT_MAIN = frozenset("nav header footer aside form button menu dialog head title".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
ENDS_ITSELF = frozenset("p li dt dd tr td th option".split())
HOLDS = frozenset("ul ol dl table div article main section body".split())
#: Words of class, id and role attributes that mark what is not main text.
_BAD = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|adsense|banner|sponsor\w*|promo\w*|comments?|disqus|respond|cookies?|consent|gdpr|notice|popup|modal|newsletter|subscribe|sidebar|side|widget|related|recommended|share|sharing|social|breadcrumbs?|nav|navbar|navigation|menu|header|masthead|footer|foot|copyright|pagination|pager|login|search|toolbar|complementary|contentinfo)(?:$|[\s_-])", re.I)
#: Quotes count after = alone; a tag or a quoted value without an end goes to the page's end, and no position is tried twice.
_TAG = re.compile(r"<!--.*?(?:-->|$)|<!\[CDATA\[.*?(?:\]\]>|$)|<[!?][^>]*(?:>|$)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?:[^>=]|=\s*+(?:\"[^\"]*+(?:\"|$)|'[^']*+(?:'|$))?)*+)(?:>|$)", re.S)
_ATTR = re.compile(r"([^\s=/>\"']+)(?:\s*=\s*(?:\"([^\"]*)\"?|'([^']*)'?|([^\s>]*)))?")
#: Of these, what an article or main element may still be; and words that tell a wrapper's layout, not its content.
_READERS = re.compile(r"(?:^|[\s_-])(?:ads?|advert\w*|sponsor\w*|promo\w*|comments?|related|recommended|teaser)(?:$|[\s_-])", re.I)
_STATE = re.compile(r"(?:has|with|without|no|is|show|hide)[_-]", re.I)
_MAIN = re.compile(r"(?:^|\s)(?:main|articlebody|article-body|post-content|entry-content)(?:$|\s)", re.I)
_NONE = re.compile(r"(?:^|;)\s*(?:display\s*:\s*none|visibility\s*:\s*hidden)", re.I)
_SPACE = re.compile(r"\s+")
#: Bits of the map that tells which runs may equal a short block.
BITS = 26
#: Where a block stands; what is in a form outside the main region is dropped as well.
DROP, OUTSIDE, MAIN, FORM = range(4)


def attributes(inside: str) -> dict[str, str]:
    """The attributes of a tag by lower-case name; the first of a name counts."""
    out: dict[str, str] = {}
    for name, *values in _ATTR.findall(inside):
        out.setdefault(name.lower(), next((v for v in values if v), ""))
    return out


def _place(name: str, inside: str, place: int) -> int:
    """Where the content of an element stands, inside one that stands at ``place``."""
    if place in (DROP, FORM) and name not in ("main", "article")[: 1 + (place == FORM)]:
        return place  # a main region may lie in a form or a marked wrapper around the whole page
    said = ""
    if inside and "=" in inside or "hidden" in inside:
        has = attributes(inside)
        if has.get("hidden", "until-found") != "until-found" or has.get("aria-hidden", "").lower() == "true" or _NONE.search(has.get("style", "")):
            return DROP
        said = " ".join(x for k in ("class", "id", "role") for x in has.get(k, "").split() if not _STATE.match(x))
    if name in ("article", "main"):
        return DROP if said and _READERS.search(said) else MAIN
    if said and _BAD.search(said) and name not in ("html", "body"):
        return DROP
    if name in NOT_MAIN:
        return FORM if name == "form" and place == OUTSIDE else DROP
    return MAIN if said and _MAIN.search(said) else place


def blocks(page: str | None) -> list[tuple[int, str]]:
    """(place, text) of the page's non-empty blocks in order."""
    out: list[tuple[int, str]] = []
    part: list[str] = []
    stack: list[tuple[str, int]] = []
    opened: Counter = Counter()
    place = OUTSIDE
    at, text = 0, page or ""

    def flush():
        if part:
            t = _SPACE.sub(" ", _html.unescape("".join(part))).strip()
            part.clear()
            if t:
                out.append((DROP if place == FORM else place, t))

    def close(name: str, within=frozenset()) -> int | None:
        """Where the innermost open ``name`` lies in the stack, unless one of ``within`` lies inside it."""
        if opened[name]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    return k
                if stack[k][0] in within:
                    return None

    def leave(k: int) -> int:
        opened.subtract(x for x, _ in stack[k:])
        del stack[k:]
        return stack[-1][1] if stack else OUTSIDE

    while True:
        m = _TAG.search(text, at)
        if m is None:
            part.append(text[at:])
            break
        if m.start() > at:
            part.append(text[at : m.start()])
        at = m.end()
        name = m[2]
        if name is None:
            continue
        name = name.lower()
        if m[1]:
            k = close(name)
            if name in BLOCKS or k is not None and place != (stack[k - 1][1] if k else OUTSIDE):
                flush()
            if k is not None:
                place = leave(k)
            continue
        if name in RAW:
            if not m[3].endswith("/"):
                end = re.compile(rf"</{name}(?:\s[^>]*)?>", re.I).search(text, at)
                at = end.end() if end else len(text)
            continue
        if name in BLOCKS:
            flush()
        if name in VOID or m[3].endswith("/"):
            continue
        if name in ENDS_ITSELF and (k := close(name, HOLDS)) is not None:  # an open one of the same kind ends here
            place = leave(k)
        here = _place(name, m[3], place)
        if here != place and name not in BLOCKS:
            flush()
        stack.append((name, here))
        opened[name] += 1
        place = here
    flush()
    return out


def host(url: str | None) -> str:
    return re.sub(r"^[a-z][a-z0-9+.-]*://(?:[^/@]*@)?", "", (url or "").strip().lower()).split("/")[0].split("?")[0].split("#")[0]


def suffix_array(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Suffix array by prefix doubling, and the longest common prefix of each suffix with the one before it in the array."""
    n = len(x)
    _, rank = np.unique(x, return_inverse=True)
    levels, k = [rank.astype(np.int64)], 1
    while k < n and levels[-1].max() + 1 < n:
        r = levels[-1]
        second = np.full(n, -1, np.int64)
        second[:-k] = r[k:]
        key = r * (n + 1) + second + 1
        _, r2 = np.unique(key, return_inverse=True)
        levels.append(r2.astype(np.int64))
        k *= 2
    sa = np.argsort(levels[-1], kind="stable")
    a, b = sa[:-1].copy(), sa[1:].copy()
    lcp = np.zeros(n, np.int64)
    for j in range(len(levels) - 1, -1, -1):  # levels[j] ranks substrings of 2**j tokens
        step = 1 << j
        ok = (a + step <= n) & (b + step <= n)
        same = np.zeros(len(a), bool)
        same[ok] = levels[j][a[ok]] == levels[j][b[ok]]
        a[same] += step
        b[same] += step
        lcp[1:][same] += step
    return sa, lcp


def repeated(streams: list[list[list[str]]], pages: list[int], least: int) -> list[list[np.ndarray]]:
    """Mask of the tokens of each block that a substring of ``least`` tokens, or of the whole block, shared with another page covers."""
    code: dict[str, int] = {}
    flat, owner, spans = [], [], []
    mark = -1
    for i, bl in enumerate(streams):
        for b in bl:
            flat += [code.setdefault(t, len(code)) for t in b]
            flat.append(mark)  # a separator that occurs once
            owner += [pages[i]] * (len(b) + 1)
            spans.append(len(b))
            mark -= 1
    if not flat:
        return [[] for _ in streams]
    x, who = np.array(flat, np.int64), np.array(owner, np.int64)
    sa, lcp = suffix_array(x)
    n = len(x)
    # longest match of each suffix with another page's: over a run of one page in the array, the least prefix back to the run's neighbour
    far, own = np.zeros(n, np.int64), who[sa]
    run = np.concatenate(([0], np.cumsum(own[1:] != own[:-1])))
    reset = np.int64(n + 1)
    before = np.minimum.accumulate(lcp - run * reset) + run * reset
    after = np.append(lcp[1:], 0)[::-1]
    back = run[-1] - run[::-1]
    after = (np.minimum.accumulate(after - back * reset) + back * reset)[::-1]
    far[sa] = np.maximum(before, after)
    size = np.repeat(spans, [s + 1 for s in spans])
    inside = np.concatenate([np.arange(s + 1) for s in spans])
    far = np.minimum(far, size - inside)
    enough = (far >= least) | (far >= size) & (inside == 0) & (size > 0)
    d = np.zeros(n + 1, np.int64)
    start = np.flatnonzero(enough & (inside < size))
    np.add.at(d, start, 1)
    np.add.at(d, start + far[start], -1)
    cover = np.cumsum(d[:-1]) > 0
    out, at = [], 0
    for bl in streams:
        mine = []
        for b in bl:
            mine.append(cover[at : at + len(b)])
            at += len(b) + 1
        out.append(mine)
    return out


def grams(stream: list[list[str]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the stream's tokens; the size of each token's block and its place in it."""
    sizes = np.array([len(b) for b in stream], np.int64)
    h = C.hashed([t.encode("utf-8", "surrogatepass") for b in stream for t in b])
    return h, np.repeat(sizes, sizes), np.arange(len(h)) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def runs(h: np.ndarray, size: np.ndarray, inside: np.ndarray, width: int, whole: bool) -> tuple[np.ndarray, np.ndarray]:
    """Starts and hashes of the runs of ``width`` tokens inside a block, or of those that are a whole block."""
    r = C.rolling(h, width)
    s, i = size[: len(r)], inside[: len(r)]
    at = np.flatnonzero((s == width) & (i == 0) if whole else i + width <= s)
    return at, r[at]


def covered_by(known: np.ndarray, streams: list[list[list[str]]], least: int) -> list[list[np.ndarray]]:
    """The masks of ``repeated`` by the sorted hashes of the runs of ``least`` tokens, and of shorter whole blocks, that other pages share."""
    flat = [b for stream in streams for b in stream]
    g = grams(flat)
    d = np.zeros(len(g[0]) + 1, np.int64)
    for w in range(1, least + 1) if len(known) else ():
        at, r = runs(*g, w, w < least)
        at = at[known[np.minimum(np.searchsorted(known, r), len(known) - 1)] == r]
        d[at] += 1
        d[at + w] -= 1
    masks = iter(np.split(np.cumsum(d[:-1]) > 0, np.cumsum([len(b) for b in flat])[:-1]) if flat else ())
    return [[next(masks) for _ in stream] for stream in streams]


def _stream(places, texts) -> list[list[str]]:
    """The blocks of a page that join its host's stream."""
    return [x.split() for k, x in zip(places, texts) if k != MAIN]


def _hosts(batches):
    for batch in batches:
        yield pa.record_batch([pa.array([host(u) for u in batch.column(0).to_pylist()], pa.string())], names=["host"])


def _hot_streams(batches, shards: dict[str, int]):
    """Ids, hosts, salts and streams of the pages, a batch at a time, of hosts that are dealt in shards."""
    for batch in batches:
        names = [host(u) for u in batch.column(1).to_pylist()]
        keep = [i for i, x in enumerate(names) if x in shards]
        if keep:
            batch = batch.take(pa.array(keep))
            names = [names[i] for i in keep]
            parsed = map(blocks, batch.column(2).to_pylist())
            yield batch.column(0), names, [deal % shards[x] for deal, x in zip(batch.column(3).to_pylist(), names)], [_stream(*zip(*b)) if b else [] for b in parsed]


def _short(shared, least: int):
    """Bits, from 1, of the blocks of less than ``least`` tokens."""

    def run(batches):
        for *_, streams in _hot_streams(batches, shared.value):
            g = grams([b for stream in streams for b in stream])
            bits = np.concatenate([g[0][:0], *(runs(*g, w, True)[1] for w in range(1, least))]) >> C.U64(64 - BITS)
            yield pa.record_batch([pa.array(np.unique(bits).astype(np.int64) + 1)], names=["bit"])

    return run


def _runs(shared, bitmap, least: int):
    """Distinct runs of each page: those of ``least`` tokens and whole shorter blocks (asked), and what may equal a shorter block of another page."""

    def run(batches):
        is_short = np.frombuffer(zlib.decompress(bitmap.value), np.uint8)
        for ids, names, salts, streams in _hot_streams(batches, shared.value):
            g = grams([b for stream in streams for b in stream])
            owner = np.repeat(np.arange(len(streams)), [sum(map(len, stream)) for stream in streams])
            found = [(*runs(*g, least, False), 1)]
            for w in range(1, least):
                found.append((*runs(*g, w, True), 1))
                at, r = runs(*g, w, False)
                bit = r >> C.U64(64 - BITS)
                may = is_short[(bit >> C.U64(3)).astype(np.int64)] >> (bit & C.U64(7)).astype(np.uint8) & 1 == 1
                found.append((at[may], r[may], 0))
            page, h = np.concatenate([owner[at] for at, _, _ in found]), np.concatenate([r for _, r, _ in found])
            asked = np.concatenate([np.full(len(r), x, np.int32) for _, r, x in found])
            order = np.lexsort((1 - asked, h, page))
            page, h, asked = page[order], h[order], asked[order]
            first = np.ones(len(h), bool)
            first[1:] = (page[1:] != page[:-1]) | (h[1:] != h[:-1])
            page, h, asked = page[first], h[first], asked[first]
            whose = ids.take(pa.array(page))
            yield pa.record_batch([pa.array(names, pa.string()).take(pa.array(page)), pa.array(salts, pa.int32()).take(pa.array(page)), pa.array(h.view(np.int64)), whose, whose, whose.is_null().cast(pa.int64()), pa.array(asked)], names=["host", "salt", "h", "low", "high", "alone", "asked"])

    return run


def _parse(shared):
    def run(batches):
        for batch in batches:
            kinds, whats, hosts, salts = [], [], [], []
            for url, t, deal in zip(*(batch.column(i).to_pylist() for i in (1, 2, 3))):
                b = blocks(t)
                kinds.append(bytes(k for k, _ in b))
                whats.append([x for _, x in b])
                hosts.append(host(url))
                salts.append(deal % shared.value.get(hosts[-1], 1))
            yield pa.record_batch([pa.array(hosts, pa.string()), pa.array(salts, pa.int32()), batch.column(0), batch.column(1), pa.array(kinds, pa.binary()), pa.array(whats, pa.list_(pa.string()))], names=["host", "salt", "page_id", "url", "places", "blocks"])

    return run


def _resolve(shared, least: int):
    def texts(rows, covered):
        out = []
        for r, mine in zip(rows, covered):
            main, left, text = MAIN in r["places"], iter(mine), []
            for k, x in zip(r["places"], r["blocks"]):
                if main and k == MAIN:
                    text.append(x)
                    continue
                gone = next(left)
                if k != DROP:
                    kept = " ".join(t for t, g in zip(x.split(), gone) if not g) if gone.any() else x
                    if kept:
                        text.append(kept)
            out.append("\n".join(text))
        return pa.record_batch([pa.array([r["page_id"] for r in rows], pa.int64()), pa.array([r["url"] for r in rows], pa.string()), pa.array(out, pa.string()), pa.array([len(t) for t in out], pa.int64()), pa.array([int(sum(int(g.sum()) for g in m)) for m in covered], pa.int64())], names=["page_id", "url", "text", "n_chars", "n_boilerplate"])

    def whole(rows):
        """A host's pages by one suffix array."""
        code: dict = {}
        pages = [code.setdefault(("row", i) if r["page_id"] is None else r["page_id"], len(code)) for i, r in enumerate(rows)]
        return texts(rows, repeated([_stream(r["places"], r["blocks"]) for r in rows], pages, least))

    def run(batches):
        rows, key, found, known = [], None, [], None
        for batch in batches:
            ready = []
            for r in batch.to_pylist():
                if (r["host"], r["salt"]) != key:
                    if rows:
                        yield whole(rows)
                    if ready:
                        yield texts(ready, covered_by(known, [_stream(x["places"], x["blocks"]) for x in ready], least))
                    key, rows, ready, found, known = (r["host"], r["salt"]), [], [], [], None
                if r["h"] is not None:
                    found.append(r["h"])
                elif r["host"] in shared.value:
                    if known is None:  # the shard's shared runs came before its pages
                        known = np.sort(np.array(found, np.int64).view(C.U64))
                    ready.append(r)
                else:
                    rows.append(r)
            if ready:
                yield texts(ready, covered_by(known, [_stream(x["places"], x["blocks"]) for x in ready], least))
        if rows:
            yield whole(rows)

    return run


def _shared_runs(p: DataFrame, shared, least: int) -> DataFrame:
    """(host, salt, h): the runs of each shard that two distinct pages of its host have, in whatever shards."""
    spark = p.sparkSession
    bits = p.mapInArrow(C.task(_short(shared, least)), "bit long")
    bitmap = C.bitmap(bits, BITS)
    found = p.mapInArrow(C.task(_runs(shared, spark.sparkContext.broadcast(zlib.compress(bitmap, 1)), least)), "host string, salt int, h long, low long, high long, alone long, asked int")
    found = found.groupBy("host", "salt", "h").agg(F.min("low").alias("low"), F.max("high").alias("high"), F.sum("alone").alias("alone"), F.max("asked").alias("asked"))
    everywhere = W.partitionBy("host", "h")  # one row a shard at most
    found = found.withColumns({"low": F.min("low").over(everywhere), "high": F.max("high").over(everywhere), "alone": F.sum("alone").over(everywhere)})
    return found.where("asked = 1 and (alone > 1 or alone = 1 and low is not null or low < high)").select("host", "salt", "h")


def extract(pages: DataFrame, least: int = 8, most_pages: int = 500) -> DataFrame:
    """(page_id, url, text, n_chars, n_boilerplate) of every page; n_boilerplate counts the tokens outside the main region that the host's other pages repeat.

    Hosts of more than ``most_pages`` pages are worked on in shards, with the same result."""
    spark = pages.sparkSession
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    counts = p.select("url").mapInArrow(C.task(_hosts), "host string").groupBy("host").count()
    # at most one host for each most_pages pages
    shared = spark.sparkContext.broadcast({r.host: -(-r["count"] // most_pages) for r in counts.where(F.col("count") > most_pages).collect()})
    p = p.withColumn("deal", F.xxhash64("page_id", "html"))
    dealt = p.mapInArrow(C.task(_parse(shared)), "host string, salt int, page_id long, url string, places binary, blocks array<string>").withColumn("h", F.lit(None).cast("long"))
    if shared.value:
        dealt = dealt.unionByName(_shared_runs(p, shared, least), allowMissingColumns=True)
    dealt = dealt.repartition(C.shuffle_width(spark), "host", "salt").sortWithinPartitions("host", "salt", F.col("h").asc_nulls_last(), "page_id")
    return dealt.mapInArrow(C.task(_resolve(shared, least)), "page_id long, url string, text string, n_chars long, n_boilerplate long")


def op1_html_extract(spark, sf_dir: str) -> DataFrame:
    return extract(C.table(spark, sf_dir, "pages"))
