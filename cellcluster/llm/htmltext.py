"""Main text of web pages: page structure and a suffix array over the pages of each host.

A page is read into blocks of text: those of a marked article (``article`` or
``main``), those that markup names as menu, notice, advert, form or comment, and
those it says nothing of. Of all pages of a host the token streams of all blocks
are concatenated, the suffixes are sorted, and runs of equal prefixes over
distinct pages are the repeated substrings. The substrings of
``LONG`` or more tokens that occur on a second page cover exactly the tokens in
windows of ``LONG`` that do, so the suffixes are sorted to that depth.

A block is boilerplate where repeats cover half of it; unique runs stay. Markup
is an exact check of that verdict and decides where the two disagree: copied
articles repeat, and menus and adverts that differ on each page do not. Streams
that are equal as a whole count as one page, so a copied page does not erase its
twin. Windows that touch a marked article repeat among such windows only, so an
article is no evidence against what another page leaves unmarked.

A host is dealt over shards of pages, whatever their texts; of streams that are
equal as a whole, the smallest shard that has one keeps it. A shard sorts its own
suffixes, a million tokens at a time, and hands on fingerprints of its runs by
range, as sorted sets in few bits: those of one of its streams, those of several,
and those of copies only, which ask and do not count. As no other stream is in two
shards, what two shards hand on is on two pages. A range is merged by one task, and
a shard gets back those of its runs that repeat.
"""

from __future__ import annotations

import html as entities
import json
import re
import struct
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import add_columns, durable, field, table
from .urlfilter import host_of
from .wordhash import mix, word_hashes

#: Tokens of the shortest long substring; share of a block that repeats cover to make it boilerplate.
LONG, COVERED = 8, 0.5
#: Pages of a shard on average, and tokens of one array.
SHARD, ARRAY = 512, 1 << 20
#: Words outside and inside of marked articles, and those of them that repeats cover.
COUNTS = ("n_outside", "n_repeated", "n_inside", "n_inside_repeated")
#: Hosts of several shards that a broadcast may list; more are joined.
WIDE_HOSTS = 200_000
#: What markup says of a block.
SILENT, ARTICLE, NAMED = 0, 1, 2
#: Tells fingerprints of windows that touch a marked article from those of others.
INSIDE = np.uint64(0x9E3779B97F4A7C15)
#: Number of packed fingerprints, and how many of their first bits agree in what.
HEAD = struct.Struct("<IBQ")
#: Sets of fingerprints that a shard hands on: of one of its streams, of several, and of streams that another shard keeps.
KINDS = ("once", "several", "asked")
ONCE, SEVERAL, ASKED = range(3)

# Elements by role, and words of class, id or role that name what is not the article.
RAW = frozenset({"script", "style", "noscript", "template", "iframe", "svg", "object", "canvas", "audio", "video", "textarea", "title"})
GONE = frozenset({"head", "nav", "footer", "aside", "form", "menu", "dialog", "button", "select", "fieldset"})
INLINE = frozenset({"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "img", "br", "math", "mi", "mn", "mo", "mrow", "ms", "mtext", "msup", "msub", "msubsup", "mfrac", "msqrt", "mroot", "mspace", "mstyle", "semantics"})
VOID = frozenset({"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"})
MARKED = frozenset({
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "adsense", "banner", "sponsor", "sponsored", "promo", "promoted",
    "sidebar", "menu", "nav", "navbar", "navigation", "breadcrumb", "breadcrumbs", "pager", "pagination", "footer", "masthead", "topbar",
    "notice", "cookie", "cookies", "consent", "gdpr", "popup", "modal", "newsletter", "subscribe", "subscription", "signup", "login",
    "comment", "comments", "respond", "reply", "replies", "disqus", "share", "sharing", "social", "related", "recommended", "widget",
    "contentinfo", "complementary", "search", "alert", "alertdialog", "dialog",
})
BOXES = frozenset({
    "area", "bar", "block", "body", "bottom", "box", "button", "buttons", "card", "col", "column", "container", "content", "form", "frame", "group", "header", "holder", "icons", "inner", "item",
    "items", "left", "link", "links", "list", "main", "message", "outer", "page", "panel", "policy", "post", "posts", "primary", "right", "row", "secondary", "section", "site", "slot", "space",
    "text", "thread", "title", "top", "unit", "wrap", "wrapper", "zone",
})

HEADINGS = frozenset({"h1", "h2", "h3", "h4", "h5", "h6"})

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(?P<end>/?)(?P<tag>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attrs>(?:[^<>\"']|\"[^\"]*\"|'[^']*'|[\"'])*)(?:>|\Z|(?=<))",
    re.S,
)
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_HIDDEN = re.compile(r"""(?:^|\s)(?:hidden(?=\s|$|=)|aria-hidden\s*=\s*["']?true)|display\s*:\s*none""", re.I)


def _unwanted(attrs: str) -> bool:
    """Whether a class, id or role is a marked word, or made of marked words and words for boxes; ``related-work`` is neither."""
    if not attrs.strip():
        return False
    for m in _NAMES.finditer(attrs):
        for name in (m[1] or m[2] or m[3] or "").lower().split():
            parts = [p for p in re.split("[-_]+", name) if p and not p.isdigit()]
            if name in MARKED or any(p in MARKED for p in parts) and all(p in MARKED or p in BOXES for p in parts) and parts[-1] not in ("body", "content", "article"):
                return True
    return bool(_HIDDEN.search(attrs))


def parse(page: str) -> list[tuple[str, int]]:
    """Blocks of text in page order, each with what markup says of it.

    Unknown, unclosed and cut-off markup is read as browsers do: an end tag
    without a start is ignored, the end of the page closes everything. A raw
    element that is closed in its own tag, or never, takes no text with it;
    scripts and styles that are never closed take the rest. The header of an
    article belongs to it, one outside is no article text.
    """
    out: list[tuple[str, int]] = []
    held, named = [], []  # text of the block at hand, and what an inline element of it names as something else
    stack: list[tuple[str, str]] = []  # element, what it is: gone, article, header or plain
    gone = article = header = 0

    def flush() -> None:
        for parts, kind in ((held, ARTICLE if article else SILENT), (named, NAMED)):
            text = "".join(parts)
            text = " ".join((entities.unescape(text) if "&" in text else text).split())
            if text:
                out.append((text, kind))
            parts.clear()

    def close(k: int) -> None:
        nonlocal gone, article, header
        for _, kind in stack[k:]:
            gone -= kind == "gone"
            article -= kind == "article"
            header -= kind == "header"
        del stack[k:]

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if (m.start() if m else n) > at:
            (named if gone or header else held).append(page[at : m.start() if m else n])
        if not m:
            break
        at = m.end()
        if m["cdata"] is not None:
            (named if gone or header else held).append(m["cdata"])
        if m["tag"] is None:
            continue
        tag, attrs = m["tag"].lower(), m["attrs"]
        if tag not in INLINE and tag not in RAW:
            flush()
        elif tag == "br":
            held.append(" ")
        if m["end"]:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    close(k)
                    break
                if stack[k][0] in ("article", "main", "body") and tag in ("p", "li", "b", "i", "span", "a", "div"):
                    break  # a stray end tag does not leave the article
            continue
        if tag in VOID or attrs.rstrip().endswith("/"):
            continue
        if tag in RAW:
            end = re.compile(rf"</{tag}\s*>", re.I).search(page, at)
            at = end.end() if end else n if tag in ("script", "style") else at
            continue
        if tag == "p" or tag in HEADINGS or tag in ("div", "ul", "ol", "section", "article", "main", "footer", "aside", "nav", "header", "table", "form"):
            if stack and stack[-1][0] == "p":
                close(len(stack) - 1)
        elif tag in ("li", "dt", "dd", "td", "th", "tr", "option") and stack and stack[-1][0] == tag:
            close(len(stack) - 1)
        if tag == "body":
            close(0)
        if tag in ("article", "main") and gone:
            # an unclosed menu or head ends where the article starts
            k = next(k for k, x in enumerate(stack) if x[1] == "gone")
            if stack[k][0] in ("nav", "head", "menu"):
                close(k)
        kind = "gone" if tag in GONE or _unwanted(attrs) else "article" if tag in ("article", "main") else "header" if tag == "header" and not article else "plain"
        gone += kind == "gone"
        article += kind == "article"
        header += kind == "header"
        stack.append((tag, kind))
    flush()
    return out


def repeated_runs(stream: np.ndarray, page: np.ndarray, depth: int = LONG) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The suffix array of the stream to ``depth`` tokens: order, start of each run of equal prefixes, their pages, and their fingerprints.

    ``page`` has the page of each position and must not decrease; a suffix that
    runs out of its page before ``depth`` tokens takes no part.
    """
    n = len(stream)
    if n < depth:
        return (np.empty(0, np.int64),) * 3 + (np.empty(0, np.uint64),)
    # the rank is the number of smaller suffixes, so one that is alone with its rank is settled
    _, own, many = np.unique(stream, return_inverse=True, return_counts=True)
    rank = (np.cumsum(many) - many)[own]
    open_ = np.flatnonzero(many[own] > 1)
    print_ = mix(stream.astype(np.uint64))
    width = 1
    while width < depth:
        step = min(width, depth - width)
        other = np.full(n, -1, np.int64)
        other[: n - step] = rank[step:]
        ok = np.zeros(n, bool)
        ok[: n - step] = page[step:] == page[: n - step]
        other[~ok] = -1
        with np.errstate(over="ignore"):
            later = np.zeros(n, np.uint64)
            later[: n - step] = print_[step:]
            print_ = mix(print_ * np.uint64(31) + np.where(ok, later, np.uint64(7)))
        key = rank[open_] * (n + 2) + other[open_] + 1
        order = np.argsort(key, kind="stable")
        key, open_ = key[order], open_[order]
        at, old = np.arange(len(key)), rank[open_]
        fresh, group = (np.maximum.accumulate(np.where(np.r_[True, v[1:] != v[:-1]][: len(v)], at, 0)) for v in (key, old))
        rank[open_] = old + fresh - group
        single = (fresh == at) & np.r_[fresh[1:] == at[1:], True][: len(at)]
        open_ = open_[~single]
        width += step
    left = np.searchsorted(page, page, side="right") - np.arange(n)
    whole = np.flatnonzero(left >= depth)
    order = whole[np.argsort(rank[whole], kind="stable")]
    first = np.flatnonzero(np.r_[True, rank[order[1:]] != rank[order[:-1]]]) if len(order) else order
    return order, first, page[order], print_[order]


def _tokens(blocks: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Word hashes of a page with a mark after each block, and the block of each token."""
    raw = [b.encode("utf-8", "surrogatepass") for b in blocks]
    size = np.array([len(b.split()) + 1 for b in raw], np.int64)
    owner = np.repeat(np.arange(len(raw)), size)
    stream, word = np.full(len(owner), 11, np.uint64), np.ones(len(owner), bool)
    word[np.cumsum(size) - 1] = False
    stream[word] = word_hashes(b"\n".join(raw))
    return stream, owner


def window_prints(stream: np.ndarray, depth: int = LONG) -> np.ndarray:
    """Fingerprints of all windows of ``depth`` tokens, those that ``repeated_runs`` gives its runs."""
    print_, width = mix(stream.astype(np.uint64)), 1
    while width < depth and len(print_):
        step = min(width, depth - width)
        with np.errstate(over="ignore"):
            print_ = mix(print_[:-step] * np.uint64(31) + print_[step:])
        width += step
    return print_


def _pack(blocks: list[tuple[str, int]]) -> bytes:
    return zstandard.compress(json.dumps(blocks, ensure_ascii=False).encode(), 3)


def _unpack(page: bytes) -> list[list]:
    return json.loads(zstandard.decompress(page))


def _touching(inside: np.ndarray, depth: int = LONG) -> np.ndarray:
    """Whether the ``depth`` tokens from each on, or those left, have one of a marked article."""
    seen = np.r_[0, np.cumsum(inside)]
    return seen[np.minimum(np.arange(len(inside)) + depth, len(inside))] > seen[:-1]


def _name(blocks: list) -> int:
    """A digest of what makes the stream of a page: its words without regard to A-Z or a-z, and where blocks end."""
    return max(1, xxhash.xxh3_64_intdigest("\n".join(t for t, _ in blocks).encode("utf-8", "surrogatepass").lower()) >> 1)


def _arrays(pages: list[bytes], gone: frozenset[int] = frozenset()) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Fingerprints of the runs of distinct streams of whole pages but those of ``gone``, each with the digest of its stream, or 0 if it has several."""
    held, touch, names, size, seen = [], [], [], 0, set()

    def sort() -> tuple[np.ndarray, np.ndarray]:
        order, first, page, prints = repeated_runs(np.concatenate(held), np.repeat(np.arange(len(held)), [len(s) for s in held]))
        if not len(order):
            return np.empty(0, np.uint64), np.empty(0, np.uint64)
        inside, digests = np.concatenate(touch)[order], np.array(names, np.uint64)
        out = []
        for own, mark in ((~inside, np.uint64(0)), (inside, INSIDE)):
            least = np.minimum.reduceat(np.where(own, page, len(held)), first)
            most = np.maximum.reduceat(np.where(own, page, -1), first)
            has = most >= 0
            out.append((prints[first][has] ^ mark, np.where(least[has] == most[has], digests[least[has]], np.uint64(0))))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    for packed in pages:
        blocks = _unpack(packed)
        name = _name(blocks)
        if name in seen or name in gone:
            continue
        seen.add(name)
        stream, owner = _tokens([t for t, _ in blocks])
        if len(stream) < LONG:
            continue
        held.append(stream)
        touch.append(_touching(np.array([kind == ARTICLE for _, kind in blocks])[owner]))
        names.append(name)
        size += len(stream)
        if size >= ARRAY:
            yield sort()
            held, touch, names, size = [], [], [], 0
    if held:
        yield sort()


#: Fingerprints whose bits are spread out at a time.
SPREAD = 1 << 16


def pack_prints(prints: np.ndarray, known: int = 0) -> bytes:
    """Ascending distinct fingerprints that agree in their first ``known`` bits, all of them kept.

    As many of their next bits as number them are written as steps, two bits a
    fingerprint, and the rest as they are.
    """
    n = len(prints)
    steps = min(max(n, 1).bit_length() - 1, 64 - known)
    rest = 64 - known - steps
    high = (prints >> np.uint64(rest) & np.uint64((1 << steps) - 1)).astype(np.int64) if steps else np.zeros(n, np.int64)
    marks = np.zeros(n + (1 << steps), np.uint8)
    marks[high + np.arange(n)] = 1
    low = [np.packbits(np.unpackbits(prints[k : k + SPREAD].astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)[:, 64 - rest :]).tobytes() for k in range(0, n, SPREAD)]
    first = int(prints[0]) >> (64 - known) if n and known else 0
    return b"".join([HEAD.pack(n, known, first), np.packbits(marks).tobytes(), *low])


def unpack_prints(packed: bytes) -> np.ndarray:
    n, known, first = HEAD.unpack_from(packed)
    steps = min(max(n, 1).bit_length() - 1, 64 - known)
    rest, data = 64 - known - steps, np.frombuffer(packed, np.uint8, offset=HEAD.size)
    size = (n + (1 << steps) + 7) // 8
    high = np.flatnonzero(np.unpackbits(data[:size], count=n + (1 << steps))) - np.arange(n)
    out, at = np.empty(n, np.uint64), size
    for k in range(0, n, SPREAD):
        m = min(SPREAD, n - k)
        wide = np.zeros((m, 64), np.uint8)
        wide[:, 64 - rest :] = np.unpackbits(data[at : at + (m * rest + 7) // 8], count=m * rest).reshape(m, rest)
        out[k : k + m] = np.packbits(wide, axis=1).view(">u8").ravel()
        at += (m * rest + 7) // 8
    if rest < 64:
        out |= (high.astype(np.uint64) | np.uint64(first << steps)) << np.uint64(rest)
    return out


def _asked(pages: list[bytes], names: list[int], gone: frozenset[int]) -> np.ndarray:
    """Fingerprints of the windows of the streams ``gone``."""
    first = {name: page for page, name in zip(pages, names, strict=True) if name in gone}
    found = [np.empty(0, np.uint64)]
    for packed in first.values():
        blocks = _unpack(packed)
        stream, owner = _tokens([t for t, _ in blocks])
        if len(stream) >= LONG:
            found.append(_marked(window_prints(stream), np.array([kind == ARTICLE for _, kind in blocks])[owner]))
    return np.unique(np.concatenate(found))


def _marked(prints: np.ndarray, inside: np.ndarray) -> np.ndarray:
    """Fingerprints of windows, told apart by whether they touch a marked article."""
    return np.where(_touching(inside)[: len(prints)], prints ^ INSIDE, prints)


def _shard_runs(part: pa.Table, copies: pa.Table) -> pa.Table:
    """Runs of a shard, packed by range of fingerprints: as many ranges as the host has shards. ``copies`` has the streams that another shard keeps."""
    pages, gone = part.column("page").to_pylist(), frozenset(copies.column("name").to_pylist())
    found = list(_arrays(pages, gone))
    host, shard, bits = (part.column(c)[0].as_py() for c in ("host", "shard", "bits"))
    prints, names = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.empty(0, np.uint64),) * 2
    # arrays of a shard have streams of their own, so what two of them have is on two pages
    prints, at, times = np.unique(prints, return_inverse=True, return_counts=True)
    several = times > 1
    several[at[names == 0]] = True
    if not bits:  # no other shard can repeat what only one page of this one has
        prints, several = prints[several], several[several]
    kind = np.where(several, SEVERAL, ONCE)
    if gone:
        asked = np.setdiff1d(_asked(pages, part.column("name").to_pylist(), gone), prints)
        prints, kind = np.concatenate([prints, asked]), np.concatenate([kind, np.full(len(asked), ASKED)])
        order = np.argsort(prints)
        prints, kind = prints[order], kind[order]
    range_ = (prints >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(prints), np.int64)
    cut = np.flatnonzero(np.r_[True, range_[1:] != range_[:-1]][: len(range_)])
    ends = np.r_[cut[1:], len(range_)] if len(cut) else cut
    return pa.table({
        "host": pa.array([host] * len(cut), pa.string()), "shard": pa.array([shard] * len(cut), pa.int64()), "range": pa.array(range_[cut], pa.int64()),
        **{c: pa.array([pack_prints(prints[a:b][kind[a:b] == k], bits) for a, b in zip(cut, ends, strict=True)], pa.binary()) for k, c in enumerate(KINDS)},
    })


def _merge_runs(part: pa.Table) -> pa.Table:
    """For each shard of a host the fingerprints of a range that occur on a second page, of this shard or another."""
    host, shards = part.column("host")[0].as_py(), part.column("shard").to_pylist()
    sets = [[unpack_prints(x) for x in part.column(c).to_pylist()] for c in KINDS]
    each = [x for of_kind in sets for x in of_kind]
    prints, at = np.unique(np.concatenate(each), return_inverse=True)
    ends = np.cumsum([0] + [len(x) for x in each])
    counted = [int(ends[k * len(shards)]) for k in (1, 2)]
    times = np.bincount(at[: counted[0]], minlength=len(prints))
    times[at[counted[0] : counted[1]]] = 2
    back = (times > 1)[at]
    # what several pages of a shard have needs no other, so all of it comes back
    found = [x[back[a:b]] for x, a, b in zip(each, ends, ends[1:], strict=False)]
    rows = [(s, np.sort(np.concatenate(found[k :: len(shards)]))) for k, s in enumerate(shards)]
    known = [HEAD.unpack_from(x)[1] for x in part.column(KINDS[0]).to_pylist()]
    rows = [(s, pack_prints(x, k)) for (s, x), k in zip(rows, known, strict=True) if len(x)]
    return pa.table({"host": pa.array([host] * len(rows), pa.string()), "shard": pa.array([s for s, _ in rows], pa.int64()), "again": pa.array([x for _, x in rows], pa.binary())})


def covered(blocks: list[str], again: np.ndarray, inside: list[bool] | None = None) -> np.ndarray:
    """Tokens and covered tokens of each block; ``again`` has the fingerprints of repeated windows in their order, ``inside`` tells blocks of marked articles."""
    stream, owner = _tokens(blocks)
    prints, hit = window_prints(stream), np.zeros(len(stream) + 1, np.int64)
    if inside is not None and len(prints):
        prints = _marked(prints, np.array(inside, bool)[owner])
    found = np.searchsorted(again, prints)
    at = np.flatnonzero(again[np.minimum(found, len(again) - 1)] == prints) if len(again) else found[:0]
    np.add.at(hit, at, 1)
    np.add.at(hit, at + LONG, -1)
    inside = np.cumsum(hit[:-1]) > 0
    ends = np.r_[owner[1:] != owner[:-1], True][: len(owner)]  # the mark after a block is no token of it
    return np.stack([np.bincount(owner[~ends], minlength=len(blocks)), np.bincount(owner[inside & ~ends], minlength=len(blocks))], axis=1)


def _decide(pages: pa.Table, found: pa.Table) -> pa.Table:
    again = np.sort(np.concatenate([unpack_prints(x) for x in found.column("again").to_pylist()] or [np.empty(0, np.uint64)]))
    rows = []
    for packed in pages.column("page").to_pylist():
        blocks = _unpack(packed)
        inside = np.array([kind == ARTICLE for _, kind in blocks], bool)
        n = covered([t for t, _ in blocks], again, inside)
        unique = n[:, 1] < COVERED * np.maximum(n[:, 0], 1)
        # the check: marked articles stay and named blocks go, whatever the repeats say; beside an article nothing else stays
        stays = inside if inside.any() else unique & np.array([kind == SILENT for _, kind in blocks], bool)
        text = [t for (t, _), yes in zip(blocks, stays.tolist(), strict=True) if yes]
        rows.append(("\n".join(text), *n[~inside].sum(axis=0).tolist(), *n[inside].sum(axis=0).tolist()))
    text, *counts = zip(*rows, strict=True) if rows else ((),) * 5
    return pa.table({"row": pages.column("row"), "text": pa.array(text, pa.string()), **{k: pa.array(v, pa.int64()) for k, v in zip(COUNTS, counts, strict=True)}})


def _streams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Host, shard and stream of the pages of hosts that have several shards."""
    for b in batches:
        yield b.filter(pc.greater(b.column("bits"), 0)).select(["host", "shard", "name"])


def extract(pages: DataFrame, html: str = "html", url: str = "url") -> DataFrame:
    """``pages`` without the markup column, with text, n_chars, n_outside, n_repeated, n_inside and n_inside_repeated.

    n_outside counts the words outside of marked articles, n_repeated those of
    them that long repeats over pages of the host cover; n_inside and
    n_inside_repeated do so for marked articles. Null html counts as
    empty and gives an empty text; an article without text gives what the page
    has outside of it. Each block has its white space turned into single spaces
    and character references decoded. Repeated rows agree, and count as one
    page. Null addresses and those without :// are one host. Columns with the
    names of the results are replaced; an empty table gives no row.
    """
    made = ("text", "n_chars", *COUNTS)
    kept = [c for c in pages.columns if c not in (html, *made)]
    host = F.coalesce(host_of(F.col(f"`{url}`").cast("string")), F.lit(""))
    # hosts of several shards: one row for SHARD pages at most
    sizes = pages.select(host.alias("host")).groupBy("host").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > SHARD)
    wide = durable(sizes.select(F.col("host").alias("__wide"), F.ceil(F.log2(F.col("n") / SHARD)).cast("int").alias("__bits")))

    def read():
        def work(texts):
            for b in texts:
                blocks = parse(b.decode("utf-8", "replace"))
                yield _pack(blocks), _name(blocks)

        return work

    rows = pages.select(F.struct(*[F.col(f"`{c}`") for c in kept]).alias("row"), host.alias("host"), F.col(f"`{html}`").cast("string").alias("html"))
    wide = F.broadcast(wide) if wide.count() <= WIDE_HOSTS else wide
    packed = add_columns(rows, "html", [field("page", "binary"), field("name", "bigint")], read, ["row", "host"])
    bits = F.coalesce("__bits", F.lit(0))
    # by what tells copies of a page apart; maps have no hash
    spread = ["page", *[F.col(f"row.`{c}`") for c in kept if "map<" not in pages.schema[c].dataType.simpleString()]]
    shard = F.pmod(F.xxhash64(*spread), F.pow(F.lit(2), bits).cast("bigint"))
    # one exchange, which both groupings read
    dealt = packed.join(wide, F.col("host") == F.col("__wide"), "left").select("row", "host", "page", "name", bits.alias("bits"), shard.alias("shard")).repartition("host", "shard")
    # all columns go in, so that the exchange is that of the groupings
    streams = dealt.mapInArrow(_streams, "host string, shard bigint, name bigint").distinct().groupBy("host", "name").agg(F.min("shard").alias("least"), F.collect_list("shard").alias("all")).where(F.size("all") > 1)
    copies = streams.select("host", F.explode(F.array_remove("all", F.col("least"))).alias("shard"), "name")
    runs = dealt.groupBy("host", "shard").cogroup(copies.groupBy("host", "shard")).applyInArrow(_shard_runs, f"host string, shard bigint, range bigint, {', '.join(f'{k} binary' for k in KINDS)}")
    again = runs.groupBy("host", "range").applyInArrow(_merge_runs, "host string, shard bigint, again binary")
    own = dealt.schema["row"].dataType.simpleString()
    out = dealt.groupBy("host", "shard").cogroup(again.groupBy("host", "shard")).applyInArrow(_decide, f"row {own}, text string, {', '.join(f'{k} bigint' for k in COUNTS)}")
    return out.select("row.*", "text", F.length("text").cast("bigint").alias("n_chars"), *COUNTS)


def op4_host_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages").select("page_id", "url", "html"))
