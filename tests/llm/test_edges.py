"""Edges that every operator defines: ids of any type, null ids, repeated rows, ties, clashing columns, empty tables, long texts."""

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from cellcluster.llm import bytebpe, chat, common, decontaminate, exactdup, neardup, quality, urlfilter
from cellcluster.llm.wordhash import SPACED, STRETCH, word_hashes

CLASH = "`row` string, text string, items array<int>, spans string, v string, sha string"


def test_words_of_long_texts_are_those_of_its_parts():
    words = [b"w%d" % (k % 977) for k in range(40_000)] + [b"x" * (3 * STRETCH)] + [b"end"]
    whole = word_hashes(b" ".join(words), SPACED)
    assert len(whole) == len(words) and (whole[[0, 977, -1]] == [word_hashes(w)[0] for w in (words[0], words[977], words[-1])]).all()
    assert whole[-2] == word_hashes(b"x" * (3 * STRETCH))[0] != word_hashes(b"x" * (3 * STRETCH + 1))[0]


def test_batches_are_cut_by_bytes():
    texts = pa.array(["a" * 10, None, "b" * 50, "c", "d" * 5])
    assert list(common.runs(texts, 20)) == [(0, 2), (2, 3), (3, 5)] and list(common.runs(texts.slice(0, 0), 20)) == []


def test_decontamination_with_ids_of_text_and_without_items(spark):
    rows = [("k", "one two three", [1], "s", "v", "h"), ("k", None, None, None, None, None)]
    docs = spark.createDataFrame(rows, CLASH)
    items = spark.createDataFrame([("b-2", "One, two!"), ("b-10", "two three"), (None, "one")], "item_id string, text string")
    out = decontaminate.find_contamination(docs, items).collect()
    assert [(r["row"], r["spans"], r.n_words, r.n_hit, list(r["items"]), r.contaminated) for r in out] == [("k", "s", 3, 3, ["b-10", "b-2"], True), ("k", None, 0, 0, [], False)]
    assert [r.contaminated for r in decontaminate.find_contamination(docs, items.limit(0)).collect()] == [False, False]
    assert decontaminate.find_contamination(docs.limit(0), items).count() == 0


def test_near_copies_of_repeated_ids_lose_no_unique_text(spark):
    rows = [(1, "a b c"), (2, "a b c"), (2, "q r s"), (2, "q  r s"), (None, "x"), (None, "x"), (None, None), (3, None)]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumns({"row": F.lit("k"), "v": F.lit(1)})
    out = neardup.drop_near(df).collect()
    assert sorted((str(r.doc_id), " ".join((r.text or "-").split())) for r in out) == [("1", "a b c"), ("2", "q r s"), ("3", "-"), ("None", "-"), ("None", "x")]
    assert out[0].asDict().keys() == {"doc_id", "text", "row", "v"} and out[0]["row"] == "k"
    one = neardup.drop_near(df.where("doc_id = 1 OR doc_id = 3")).collect()
    assert sorted(r.doc_id for r in one) == [1, 3]


def test_exact_copies_with_ids_of_text_and_null_ids(spark):
    rows = [("b", "x y"), ("a", "xy"), (None, "x  y"), (None, "z"), ("c", "z"), ("d", "q")]
    df = spark.createDataFrame(rows, "doc_id string, text string").withColumns({"sha": F.lit("s"), "points": F.lit(7)})
    got = {(r.doc_id, r.text_sha256[:6]): (r.keep_id, r.group_size, r.kept) for r in exactdup.group_copies(df).collect()}
    assert sorted((v for k, v in got.items() if k[0] in ("a", "b", "c", "d")), key=str) == [("c", 2, True), ("d", 1, True), (None, 3, False), (None, 3, False)]
    kept = exactdup.drop_copies(df).collect()
    assert sorted((str(r.doc_id), r.text) for r in kept) == [("None", "x  y"), ("c", "z"), ("d", "q")] and kept[0].sha == "s" and kept[0].points == 7


def test_scores_of_repeated_and_long_rows_and_no_rows(spark):
    df = spark.createDataFrame([(1, "good text", "s"), (1, "good text", "s"), (2, "bad !!! " * 60_000, "s"), (3, None, "s")], "doc_id bigint, text string, score string")
    labels = spark.createDataFrame([(1, 1), (2, 0), (None, 1), (9, 1), (2, None)], "doc_id bigint, quality int")
    out = sorted(quality.judge(df, labels).collect(), key=lambda r: r.doc_id)
    assert out[0] == out[1] and all(0 <= r.score <= 1 and r.predicted == int(r.score >= quality.THRESHOLD) for r in out)
    assert quality.judge(df.limit(0), labels).count() == 0


def test_empty_tables_and_long_addresses(spark):
    path, pattern = bytebpe.production()
    none = spark.createDataFrame([], "doc_id bigint, text string")
    assert bytebpe.add_tokens(none, path, pattern).count() == 0
    assert chat.format_chats(spark.createDataFrame([], "conv_id bigint, turn bigint, role string, text string")).count() == 0
    weights = urlfilter.fit(spark)
    pages = spark.createDataFrame([(1, "http://" + "casino-" * 4000 + ".example.org/" + "p" * 30_000, "f"), (2, None, "f"), (2, None, "f")], "page_id bigint, url string, fit string")
    out = sorted(urlfilter.judge_urls(pages, weights).collect(), key=lambda r: r.page_id)
    assert out[0].verdict == "block" and len(out[0].path) == 30_001 and out[1] == out[2] and out[1].verdict == ("block" if out[1].unwanted >= 0.5 else "allow") and out[1].fit == "f"
    assert urlfilter.judge_urls(pages.limit(0), weights).count() == 0


def test_model_on_addresses_by_another_rule(spark):
    """Words of the training table in other places and zones, and words that are in none."""
    weights = urlfilter.fit(spark)
    bad = [f"https://{a}.{z}/{p}" for a in ("best-casino", "mycheap-pills", "poker24", "xxx-adult") for z in ("shop.io", "co.uk") for p in ("", "index.html")]
    good = [f"https://{a}.{z}/{p}" for a in ("citymuseum", "river-history", "the-library", "mountain-weather") for z in ("info", "edu") for p in ("", "about")]
    df = spark.createDataFrame([(k, u) for k, u in enumerate(bad + good)], "page_id bigint, url string")
    verdicts = [r.verdict for r in sorted(urlfilter.judge_urls(df, weights, rules=()).collect(), key=lambda r: r.page_id)]
    right = np.mean([v == "block" for v in verdicts[: len(bad)]] + [v == "allow" for v in verdicts[len(bad) :]])
    assert right >= 0.85


def test_conversations_of_many_turns(spark):
    rows = [(1, t, "user", f"t{t}") for t in range(1200)] + [(2, t, "user", f"t{t}") for t in range(700)] + [(3, 0, None, None)]
    out = chat.format_chats(spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string")).collect()
    assert sorted((r.conv_id, r.part, r.n_turns) for r in out) == [(1, 0, 512), (1, 1, 512), (1, 2, 176), (3, 0, 1)]
