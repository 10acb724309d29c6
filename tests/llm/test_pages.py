"""Main text of pages: markup edges, and covered blocks against brute force over the pages of a host."""

import random

import numpy as np

from cellcluster.llm import htmltext


def texts(page, kind=htmltext.ARTICLE):
    return [t for t, k in htmltext.parse(page) if k == kind]


def test_article_text_is_not_lost():
    assert texts('<article><h1>T</h1><p>one</p><svg class="i"/><p>two</p><math/><p>three</p><iframe src=x><p>four</p><object data=o/><p>five</article>') == ["T", "one", "two", "three", "four", "five"]
    assert texts("<article><header><p>lead</p><h1>T</h1></header><p>x <math><mi>E</mi><mo>=</mo><mn>1</mn></math> y</p></article>") == ["lead", "T", "x E=1 y"]
    kept = '<div class="related-work">a</div><div class="search-results">b</div><p class="ad-hoc">c</p><p>d <span class="ad">buy</span>e</p>'
    gone = '<div class="ad-slot">n</div><ul class="related-posts"><li>n</ul><div id="comments">n</div><div hidden>n</div><p class="cookie-notice">n</p><aside>n</aside>'
    assert texts(f"<article>{kept}{gone}</article><header>n</header>") == ["a", "b", "c", "d e"]
    assert texts("<p>a<script>var x='<p>';</script>b", htmltext.SILENT) == ["ab"]


def brute_again(pages, depth):
    """Token windows that occur on two distinct streams."""
    seen = {}
    for p in {tuple(p) for p in pages}:
        for k in range(len(p) - depth + 1):
            seen.setdefault(p[k : k + depth], set()).add(p)
    return {w for w, ps in seen.items() if len(ps) > 1}


def test_covered_tokens_are_those_of_maximal_repeats():
    r = random.Random(3)
    pool = [[f"w{r.randrange(9)}" for _ in range(r.randrange(3, 30))] for _ in range(12)]
    pages = [[" ".join(r.choice(pool)) if r.random() < 0.5 else " ".join(f"u{r.randrange(400)}" for _ in range(r.randrange(1, 25))) for _ in range(r.randrange(1, 6))] for _ in range(40)]
    streams = [tuple(htmltext._tokens(p)[0].tolist()) for p in pages]
    again = brute_again(streams, htmltext.LONG)
    packed = [htmltext._pack([(t, htmltext.SILENT) for t in p]) for p in pages]
    prints, names = map(np.concatenate, zip(*htmltext._arrays(packed), strict=True))
    found = {int(p) for p in prints if len({int(n) for n, q in zip(names, prints, strict=True) if q == p} - {0}) > 1 or 0 in names[prints == p]}
    for p, s in zip(pages, streams, strict=True):
        # the longest match with another stream at each position, as a suffix array with heights would give it
        others = [o for o in set(streams) if o != s]
        inside = [False] * len(s)
        for k in range(len(s)):
            most = 0
            for o in others:
                for j in range(len(o)):
                    n = 0
                    while k + n < len(s) and j + n < len(o) and s[k + n] == o[j + n]:
                        n += 1
                    most = max(most, n)
            if most >= htmltext.LONG:
                inside[k : k + most] = [True] * most
        by_window = [False] * len(s)
        for k in range(len(s) - htmltext.LONG + 1):
            if s[k : k + htmltext.LONG] in again:
                by_window[k : k + htmltext.LONG] = [True] * htmltext.LONG
        assert inside == by_window
        at, want = 0, []
        for b in p:
            n = len(b.split())
            want.append([n, sum(inside[at : at + n])])
            at += n + 1
        assert htmltext.covered(p, np.array(sorted(found), np.uint64)).tolist() == want


def test_extract_over_shards_with_copies_and_clashing_columns(spark, monkeypatch):
    menu, foot = "Home About Contact Shop Blog Team Jobs Press Help", "Copyright by the happy company all rights reserved worldwide today"
    word = lambda k: " ".join(f"t{k}x{j}" for j in range(30))
    loose = lambda t: f"<body><div>{menu}</div><p>{t}</p><div>{foot}</div></body>"
    rows = [(k, "http://h.com/a", loose(word(k)), [k], "b", "r") for k in range(40)] + [(100 + k, "http://h.com/twin", loose(word("twin")), [k], "b", "r") for k in range(40)]
    rows += [(200, None, None, [1], "b", "r"), (201, "http://h.com/m", f"<article><p>{word(3)}</p></article><nav>{menu}</nav>", [1], "b", "r"), (202, "http://i.com", loose("x " * 200_000 + "end"), [1], "b", "r"), (203, "", "", [1], "b", "r")]
    df = spark.createDataFrame(rows, "page_id bigint, url string, html string, blocks array<int>, host string, `row` string")
    want = {k: word(k) for k in range(40)} | {100 + k: word("twin") for k in range(40)}
    # the text of a marked article is no evidence against the page that has the same
    want |= {200: "", 201: word(3), 202: "\n".join([menu, "x " * 200_000 + "end", foot]), 203: ""}
    for shard in (512, 4):
        monkeypatch.setattr(htmltext, "SHARD", shard)
        out = htmltext.extract(df).collect()
        assert {r.page_id: r.text for r in out} == want and all(r.host == "b" and r["row"] == "r" and r.n_chars == len(r.text) for r in out)
        assert {r.page_id: r.n_repeated for r in out}[201] == 9
    assert htmltext.extract(df.limit(0)).count() == 0


def test_arrays_hold_marked_articles_too(spark):
    """Repeats are found in whole pages and judge every block; markup has the last word, so a copied article stays."""
    word = lambda k: " ".join(f"t{k}x{j}" for j in range(20))
    page = lambda k, more="": f"<nav>{word('menu')}</nav><article><p>{word(k)}</p>{more}</article>"
    rows = [(k, "http://h.com/a", page(k, f"<p>{word('shared')}</p>" if k < 3 else "")) for k in range(5)] + [(9, "http://h.com/b", f"<p>{word('shared')}</p><p>{word(9)}</p>")]
    got = {r.page_id: r for r in htmltext.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()}
    assert {k: (r.n_outside, r.n_repeated, r.n_inside, r.n_inside_repeated) for k, r in got.items()} == {k: (20, 20, 40, 20) if k < 3 else (20, 20, 20, 0) for k in range(5)} | {9: (40, 0, 0, 0)}
    assert {k: r.text for k, r in got.items()} == {k: "\n".join([word(k), word("shared")][: 2 if k < 3 else 1]) for k in range(5)} | {9: f"{word('shared')}\n{word(9)}"}


def test_suffixes_of_few_tokens_are_sorted_to_their_depth():
    r = np.random.default_rng(1)
    for n, kinds in ((60, 2), (400, 3), (300, 1), (200, 500)):
        stream, page = r.integers(0, kinds, n).astype(np.uint64), np.sort(r.integers(0, 5, n))
        order, first, pages, _ = htmltext.repeated_runs(stream, page)
        window = {k: tuple(stream[k : k + htmltext.LONG].tolist()) for k in range(n - htmltext.LONG + 1) if page[k] == page[k + htmltext.LONG - 1]}
        assert order.tolist() == sorted(window, key=lambda k: (window[k], k)) and pages.tolist() == page[order].tolist()
        assert first.tolist() == [i for i, k in enumerate(order) if not i or window[k] != window[order[i - 1]]]


def test_packed_fingerprints_are_whole_and_few_bits():
    r = np.random.default_rng(2)
    for n, known in ((0, 0), (1, 0), (1, 3), (2, 0), (9, 5), (700, 0), (htmltext.SPREAD + 77, 2)):
        low = np.unique(r.integers(0, 2**64, n, dtype=np.uint64) >> np.uint64(known))
        prints = low | np.uint64(5 % (1 << known) << (64 - known)) if known else low
        packed = htmltext.pack_prints(prints, known)
        assert htmltext.unpack_prints(packed).tolist() == prints.tolist()
    assert len(packed) < 6.2 * len(prints)
    ends = np.array([0, 1, 2**63, 2**64 - 2, 2**64 - 1], np.uint64)
    assert htmltext.unpack_prints(htmltext.pack_prints(ends)).tolist() == ends.tolist()


def test_shards_hand_on_few_bytes_and_no_stream_twice(spark, monkeypatch):
    """Pages of 300 words of their own, each in two shards or more: fewer bytes than 7 a window, and copies in other shards do not count as repeats."""
    monkeypatch.setattr(htmltext, "SHARD", 4)
    text = lambda k: " ".join(f"p{k}w{j}" for j in range(300))
    rows = [(k, "http://h.com/a", f"<article><p>{text(k % 12)}</p></article>") for k in range(48)]
    got = htmltext.extract(spark.createDataFrame(rows, "page_id bigint, url string, html string")).collect()
    assert len(got) == 48 and all((r.n_inside, r.n_inside_repeated) == (300, 0) for r in got)
    pages = [htmltext._pack([(text(k), htmltext.ARTICLE)]) for k in range(400)]
    part = htmltext.pa.table({"page": pages, "host": ["h"] * 400, "shard": [1] * 400, "bits": [1] * 400, "name": [htmltext._name([(text(k), 1)]) for k in range(400)]})
    none = htmltext.pa.table({"name": htmltext.pa.array([], htmltext.pa.int64())})
    out = htmltext._shard_runs(part, none)
    size = sum(len(x) for c in htmltext.KINDS for x in out.column(c).to_pylist())
    assert 400 * 290 * 5 < size < 400 * 293 * 7
    first = htmltext.pa.table({"name": part.column("name").slice(0, 399)})
    out = htmltext._shard_runs(part, first)
    count = {c: sum(len(htmltext.unpack_prints(x)) for x in out.column(c).to_pylist()) for c in htmltext.KINDS}
    assert count == {"once": 294, "several": 0, "asked": 399 * 294}
