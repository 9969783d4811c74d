"""Nothing of the job is left out: inputs above the former caps."""

import numpy as np
import pytest
from pyspark.sql import functions as F


@pytest.mark.parametrize("listed", [2_000_000, 0])
def test_target_counts_every_trusted_document(spark, listed):
    from fsmeta.llm import quality_rules as qr

    d = spark.range(20_500).select(F.col("id").alias("doc_id"), F.concat(F.lit("w"), F.col("id") % 97).alias("text"))
    more = spark.createDataFrame([(None, "other words"), (None, None)], "doc_id long, text string")
    got = qr.log_ratios(d, d.select("doc_id"), buckets=64, listed=listed).collect()
    assert len(got) == 64 and all(r["lr"] == 0 for r in got)
    # rows without a key are counted as raw only
    some = {r["bucket"]: r["lr"] for r in qr.log_ratios(d.unionByName(more), d.select("doc_id"), buckets=64, listed=listed).collect()}
    other = {b for r in more.select(qr.grams(F.coalesce("text", F.lit("")), 64).alias("g")).collect() for b in r["g"]}
    assert len(other) > 0 and all((v < 0) == (b in other) for b, v in some.items())


def test_scores_keep_the_class_sizes(spark):
    """Texts that say nothing of their class are scored by its share, however few rows are sampled."""
    from fsmeta.llm import quality_classifier as qc

    rng = np.random.default_rng(3)
    rows = [(i, " ".join(rng.choice(["alpha", "be", "gamma,", "D", "8"], int(rng.integers(20, 60)))), int(i % 10 > 0)) for i in range(3000)]
    d = spark.createDataFrame(rows, "doc_id long, text string, quality int")
    for per_class in (3000, 300):
        m = qc.fit(d, d, F.lit(True), per_class=per_class)
        scores = [r["score"] for r in qc.score(d, m, keep=("doc_id",)).collect()]
        assert abs(np.mean(scores) - 0.9) < 0.05


def test_wrappers_with_class_words_keep_the_article():
    from fsmeta.llm.html_text import main_text

    text = " ".join(f"<p>Paragraph {i}, which goes on for a while, so that it counts as text.</p>" for i in range(4))
    want = " ".join(f"Paragraph {i}, which goes on for a while, so that it counts as text." for i in range(4))
    for wrapper in ("class='layout has-sidebar'", "id='post-with-comments'"):
        assert main_text(f"<body><h1>Site</h1><div {wrapper}><article>{text}</article><div class=sidebar>Side, text</div></div></body>") == want
        assert want in main_text(f"<body><h1>Site</h1><div {wrapper}>{text}</div><p>About us</p></body>")
    long = "<section class=comments>" + "<p>I, too, have, many, things, to say about this and that.</p>" * 30 + "</section>"
    assert main_text(f"<body><article>{text}</article>{long}</body>") == want


def test_every_language_is_learned(spark):
    from fsmeta.llm import language_id as li

    d = spark.createDataFrame([(i, f"some words {i} of it", f"l{i // 2:02d}") for i in range(140)], "doc_id long, text string, lang string")
    assert li.fit(d, F.lit(True), epochs=1).languages == [f"l{i:02d}" for i in range(70)]


def test_html_quotes_and_names():
    from fsmeta.llm.html_text import main_text

    assert main_text("<article><p class=x'>It is one thing, and it's another. More text, here.</p></article>") == "It is one thing, and it's another. More text, here."
    assert main_text("<p title='a > b' data-x = \"c>d\">text, here</p>") == "text, here"
    text = "".join(f"<p>Paragraph {i}, which goes on for a while, so that it counts as text of its own, and more of it.</p>" for i in range(5))
    for page in (f"<h1>H</h1><section id='widget-guide'>{text}</section><p>short line</p>", f"<article><h1>H</h1>{text}<section class='search-results'>{text}</section></article>"):
        assert main_text(page).count("Paragraph") == page.count("Paragraph")
    page = f"<article><h1>H</h1>{text}<div class=notice>We use cookies, as all do.</div><div class=comments>{text}</div></article>"
    assert main_text(page).count("Paragraph") == 5 and "cookies" not in main_text(page)
    assert main_text("<p>" + "word, " * 300_000 + "</p>").count("word,") == 300_000


def test_html_of_every_given_page(spark, sf):
    """The given pages hold their text in one article element without other blocks: it is the reference."""
    import re
    from html import unescape

    from fsmeta.llm.html_text import extract

    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in extract(spark.read.parquet(f"{sf}/pages.parquet")).collect():
        inside = re.search(r"<article>(.*)</article>", pages[r["page_id"]], re.S)[1]
        want = " ".join(unescape(re.sub(r"</?(?:p|h1|br|li|ul)[^>]*>", " ", inside)).split())
        assert r["text"] == " ".join(re.sub(r"</?b>|<a[^>]*>|</a>", "", want).split()) and r["n_chars"] == len(r["text"])
    assert extract(spark.read.parquet(f"{sf}/pages.parquet").limit(0)).count() == 0


def aligned(a: bytes, b: bytes) -> int:
    """Edits of the best place of a in b."""
    row = np.zeros(len(b) + 1, np.int64)
    text, steps = np.frombuffer(b, np.uint8), np.arange(len(b) + 1)
    for i, x in enumerate(a, 1):
        new = np.append(i, np.minimum(row[:-1] + (text != x), row[1:] + 1))
        row = np.minimum.accumulate(new - steps) + steps
    return int(row.min())


def test_leaks_equal_full_alignment(spark, sf):
    """Every item of the benchmark against every document of a small table."""
    import pyarrow as pa

    from fsmeta.llm import decontamination as dc

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = spark.read.parquet(f"{sf}/benchmark.parquet")
    got = {(r["doc_id"], r["item_id"]): r["edits"] for r in dc.leaks(docs, items).collect()}
    texts = [r for r in docs.collect() if r["text"] and len(r["text"]) < 6000]
    flat, at = dc.normal(pa.array([r["text"] for r in texts]))
    for it in items.collect():
        own, _ = dc.normal(pa.array([it["text"]]))
        own = own.tobytes().rstrip(b" ")
        for i, r in enumerate(texts):
            edits = aligned(own, flat[at[i] : at[i + 1]].tobytes())
            assert got.get((r["doc_id"], it["item_id"])) == (edits if edits <= int(0.1 * len(own)) else None)


def test_short_items_and_repetitive_texts():
    import pyarrow as pa

    from fsmeta.llm import decontamination as dc

    rng = np.random.default_rng(0)
    for _ in range(300):
        item = rng.integers(97, 103, int(rng.integers(1, 60))).tolist()
        e = list(item)
        for _ in range(int(rng.integers(0, len(item) // 10 + 2))):
            at = int(rng.integers(len(e))) if e else 0
            e = [e[:at] + e[at + 1 :], e[:at] + [98] + e[at:], e[:at] + [97] + e[at + 1 :]][int(rng.integers(3))]
        text = bytes(rng.integers(97, 103, 20).tolist() + e + rng.integers(97, 103, 20).tolist())
        found = list(dc.search(dc.Index([0], [bytes(item).decode()], 0.1), *dc.normal(pa.array([text.decode()]))))
        want = aligned(bytes(item), text)
        assert [f[2] for f in found] == ([want] if want <= int(0.1 * len(item)) else [])
    import tracemalloc

    tracemalloc.start()
    assert list(dc.search(dc.Index([1], ["a" * 400], 0.1), *dc.normal(pa.array(["a" * 60_000, "b" + "a" * 390])))) == [(0, 0, 0, 400), (1, 0, 9, 391)]
    assert tracemalloc.get_traced_memory()[1] < 200 << 20
    tracemalloc.stop()


def test_rows_that_look_alike_are_told_apart(spark):
    from fsmeta.llm import suffix_dedup as sd

    t = "abcdefghij" * 8
    d = spark.createDataFrame([(1, t), (None, "1|" + t), (None, "1:1|" + t), (2, None)], "doc_id long, text string")
    got = {(r["doc_id"], r["n_bytes"]): r["n_removed"] for r in sd.remove_repeats(d, length=40).collect()}
    assert got == {(1, 80): 80, (None, 82): 80, (None, 84): 82, (2, 0): 0}


def test_hot_contexts_are_added_up_in_tasks(spark):
    from fsmeta.llm import suffix_dedup as sd

    d = spark.range(4000).selectExpr("id doc_id", "repeat('the very same passage, ', 20) text").repartition(8)
    rid = sd.row_id(d["doc_id"].cast("string"), d["text"])
    repeated = sd.anchors(d, "text", 200).groupBy("h").agg(F.sum("n").alias("n")).filter("n > 1")
    found = sd.contexts(d, "text", 200, rid, repeated, 10**6)
    assert sd.combined(found).count() <= 8 * found.select("h", "cid").distinct().count()


def test_shard_elements_are_read_alone(tmp_path):
    from fsmeta.llm.store_ids import Replaced, ShardIndex

    keys = np.sort(np.random.default_rng(3).choice(1 << 40, 5000, replace=False))
    keys = np.repeat(keys, np.random.default_rng(4).integers(1, 4, len(keys)))
    idx = ShardIndex.build(keys, np.ones(len(keys), bool), np.ones(len(keys), np.int64))
    f = Replaced(str(tmp_path / "a.idx"))
    f.write(idx.dump())
    f.close()
    some = np.append(keys[::97], [3, 1 << 50])
    assert (ShardIndex.open(str(tmp_path / "a.idx")).find(some) == idx.find(some)).all()
    assert (idx.rows_of(np.unique(keys)) == np.arange(len(keys))).all()
