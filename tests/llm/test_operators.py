"""Each operator against brute force on small tables, with nulls, empties, ties, long texts and clashing columns."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

WORD = re.compile("[^\x20\x09-\x0d]+")
LOREM = "the quick brown fox jumps over the lazy dog while seven wizards brew strong potions near an old river bank"


def text_of(seed: int, n: int) -> str:
    rng = np.random.default_rng(seed)
    w = LOREM.split()
    return " ".join(w[i] + (str(int(rng.integers(1000))) if rng.random() < 0.7 else "") for i in rng.integers(0, len(w), n))


@pytest.fixture(scope="module")
def rows():
    base = text_of(1, 120)
    words = base.split()
    near = " ".join([*words[:60], "changed", *words[61:]])
    far = " ".join(w if i % 3 else "x" + w for i, w in enumerate(words))
    return [
        (1, base, "en", "a"), (2, base, "en", "a"), (3, near, "en", "b"), (4, far, "en", None), (5, None, "en", "a"), (6, "", None, "b"), (7, " \n\t", "en", "a"),
        (8, "two words", "de", "a"), (9, "two words", "de", "c"), (10, text_of(2, 4000), "en", "a"), (None, text_of(3, 50), "en", "a"), (1, base, "en", "a"),
        (12, "ein Wörtchen für alle <|endoftext|> ÉÀ 漢字 \x85 x", "de", "c"), (13, "### !! 123 |", None, "c"), (14, "a" * 5000, "en", "d"), (15, text_of(2, 3000) + " tail of its own", "en", "d"),
    ]


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumns({"k": F.lit("x"), "t": F.lit(1), "score": F.lit(2.0), "node": F.lit(None).cast("long"), "_t": F.lit("y"), "size": F.lit(3)}).repartition(3)


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def as_rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=repr)


def test_language_id(docs, none):
    from fsmeta.llm import language_id as li

    m = li.fit(docs, F.lit(True))
    got = li.identify(docs, m).collect()
    assert len(got) == 16 and all(0 <= r["score"] <= 1 for r in got)
    for r in got:
        if r["doc_id"] in (5, 6, 7, 13):
            assert r["lang_pred"] == "und" and r["score"] == 0
        else:
            assert r["lang_pred"] in ("en", "de")
    empty = li.fit(none, F.lit(True))
    assert empty is None and {r["lang_pred"] for r in li.identify(docs, empty).collect()} == {"und"}
    assert li.identify(none, m).count() == 0


def test_language_pieces_do_not_matter(monkeypatch):
    import pyarrow as pa

    from fsmeta.llm import language_id as li

    w = np.random.default_rng(1).normal(size=(li.BUCKETS, 3))
    col = pa.array([text_of(4, 500), "", None, text_of(5, 10)])
    a = li.sums(col, w)
    monkeypatch.setattr(li, "PIECE", 777)
    assert np.allclose(a, li.sums(col, w), rtol=1e-4, atol=1e-3) and (a[:, -1] == li.sums(col, w)[:, -1]).all()


def test_html():
    from fsmeta.llm.html_text import main_text

    page = """<html><head><title>T</title><style>p{}</style></head><body><nav><ul><li><a href=x>Menu, of, many, words</a></ul></nav>
    <div class="sidebar"><p>Side text, with, commas and more of it to be long.</p></div><header><h1>Site</h1></header>
    <article><header><h1>Head&amp;line</h1></header><p>First <b>bold</b> para,&nbsp;with &eacute; text.<p>Second <a href="#">link</a> one<br>broken
    <ul><li>item one<li>item two</ul><script>var x = "<p>no</p>";</script><div class="ad">Buy now</div><form>Name <input></form>
    <section class="comments"><p>I, too, have, things, to say</p></section></article><aside>More</aside><footer>&copy; foot</footer></body>"""
    assert main_text(page) == "Head&line First bold para, with é text. Second link one broken item one item two"
    assert main_text(None) == "" and main_text("") == "" and main_text("<div") == ""
    assert main_text("<p>plain words only") == "plain words only"
    assert main_text('<div class="ad-free page"><p>All of the text, in here.</p></div>') == "All of the text, in here."
    deep = "<div>" * 20_000 + "<p>deep text, here</p>" + "</div>" * 20_000
    assert main_text(deep) == "deep text, here"
    plain = "<div id=content><div class=post>" + "".join(f"<p>Paragraph {i}, which goes on for a while, so that it counts as text of its own.</p>" for i in range(4)) + "</div></div><div class=footer><a href=a>about</a></div>"
    assert main_text(plain).startswith("Paragraph 0,") and main_text(plain).endswith("its own.") and "about" not in main_text(plain)


def test_html_table(spark):
    from fsmeta.llm.html_text import extract

    df = spark.createDataFrame([(1, "u", "<article><p>hi you</p></article>", 5), (1, None, None, 6), (None, "u", "", 7)], "page_id long, url string, html string, text int")
    assert as_rows(extract(df), "page_id", "text", "n_chars") == sorted([(1, "hi you", 6), (1, "", 0), (None, "", 0)], key=repr)


def test_token_output(docs, none, rows, spark):
    from fsmeta.llm import token_output as to
    from fsmeta.llm.pretokens import load
    from fsmeta.plans import workspace

    tok = load("byte_bpe_50k.json")
    uri = workspace.fresh(spark, "test")
    to.write_tokens(docs, uri, shard_ids=700)
    got = [(r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in to.read_rows(spark, uri).collect()]
    got.sort(key=lambda r: r[1])
    keys = [r[0] for r in got]
    assert keys[0] is None and keys[1:] == sorted(keys[1:]) and len(keys) == len(rows)
    want = {}
    for k, t, *_ in rows:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 2]
        want[k] = (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
    at = 0
    for k, start, n, crc in got:
        assert start == at and want[k] == (n, crc)
        at += n
    found = to.lookup(spark, uri, [1, 10, 999])
    assert len(found[1]) == 2 and found[999] == []
    assert found[10][0].tolist() == [*tok.encode(rows[9][1], add_special_tokens=False).ids, 2]
    assert to.store_tokens(none).count() == 0


def test_perfect_hash():
    from fsmeta.llm.store_ids import PerfectHash, ShardIndex, key_hash

    keys = np.random.default_rng(2).choice(1 << 40, 20_000, replace=False)
    p = PerfectHash.build(key_hash(keys))
    assert sorted(p.slots(key_hash(keys)).tolist()) == list(range(len(keys)))
    idx = ShardIndex.parse(ShardIndex.build(np.sort(keys), np.ones(len(keys), bool), np.ones(len(keys), np.int64)).dump())
    assert (idx.find(np.sort(keys)) == np.arange(len(keys))).all() and (idx.find(keys + (1 << 41)) == -1).all()


def test_token_counts(docs, none, rows):
    from fsmeta.llm.pretokens import load
    from fsmeta.llm.token_counts import count_tokens

    tok = load("word_bpe_49k.json")
    want = sorted(((k, len((t or "").encode()), len(tok.encode(t or "", add_special_tokens=False).ids)) for k, t, *_ in rows), key=repr)
    assert as_rows(count_tokens(docs, table_size=5), "doc_id", "n_bytes", "n_tokens") == want
    assert as_rows(count_tokens(docs), "doc_id", "n_bytes", "n_tokens") == want
    assert count_tokens(none).count() == 0


def test_decontamination(spark, docs, none):
    from fsmeta.llm import decontamination as dc

    item = text_of(9, 40)
    edited = item.replace("the", "teh", 2).replace("river", "rivr", 1)
    cut = item[: len(item) // 2]
    d = spark.createDataFrame([(1, "start " + item.upper().replace(" ", ",  ") + " end"), (2, text_of(8, 300) + " " + edited + " " + text_of(7, 5000)), (3, cut), (4, None), (5, ""), (6, text_of(6, 400)), (1, "start " + item.upper())], "doc_id long, text string")
    b = spark.createDataFrame([(10, item), (11, None), (12, ""), (13, "zq"), (14, item)], "item_id long, text string")
    got = as_rows(dc.leaks(d, b), "doc_id", "item_id", "edits")
    assert [g[:2] for g in got] == sorted([(1, 10), (1, 10), (1, 14), (1, 14), (2, 10), (2, 14)]) and {g[2] for g in got if g[0] == 1} == {0}
    assert got == as_rows(dc.leaks(d, b, block_bytes=1), "doc_id", "item_id", "edits")
    assert dc.leaks(d, b.limit(0)).count() == 0 and dc.leaks(none, b).count() == 0


def test_banded_alignment_is_exact():
    from fsmeta.llm.decontamination import banded

    rng = np.random.default_rng(5)

    def brute(a, b):
        row = [0] * (len(b) + 1)
        for i, x in enumerate(a, 1):
            new = [i]
            for j, y in enumerate(b, 1):
                new.append(min(row[j - 1] + (x != y), row[j] + 1, new[-1] + 1))
            row = new
        return min(row)

    for _ in range(300):
        a = bytes(rng.integers(97, 100, int(rng.integers(5, 20))).tolist())
        b = bytes(rng.integers(97, 100, int(rng.integers(0, 30))).tolist())
        if rng.random() < 0.5:
            b = b[:7] + a[:4] + b"z" + a[5:] + b[7:]
        k, want = 3, brute(a, b)
        got = banded(a, b, k)
        assert (got[0] if got else None) == (want if want <= k else None), (a, b)


def test_mixing(docs, none, rows):
    from fsmeta.llm.mixing import mix

    got = mix(docs, block=16).collect()
    size = Counter()
    for _, t, _, s in rows:
        size[s] += len(WORD.findall(t or ""))
    names = sorted(size, key=lambda x: (x is None, x))
    weight = {n: (3, 1, 2)[i % 3] for i, n in enumerate(names)}
    left, total = set(names), 1.5 * sum(size.values())
    while True:
        rest = total - sum(2 * size[n] for n in names if n not in left)
        level = rest / sum(weight[n] for n in left)
        over = {n for n in left if level * weight[n] > 2 * size[n]}
        if not over:
            break
        left -= over
    want = {n: level * weight[n] if n in left else 2.0 * size[n] for n in names}
    by = {(k, s): (len(WORD.findall(t or "")), s) for k, t, _, s in rows}
    assert len(got) == len(rows)
    taken = Counter()
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"]
        s = next(s for (k, s), (n, _) in by.items() if k == r["doc_id"] and n == r["size"] and size[s] == r["source_size"])
        assert abs(r["target"] - want[s]) < 1e-6 * max(1, want[s])
        taken[s] += r["taken"]
    assert all(abs(taken[s] - want[s]) <= 1 for s in names)
    assert as_rows(mix(docs, block=16), "doc_id", "size", "taken") == as_rows(mix(docs.repartition(7), block=16), "doc_id", "size", "taken")
    assert mix(none).count() == 0


def test_schedule_spreads(spark, monkeypatch):
    from fsmeta.llm import mixing

    monkeypatch.setattr(mixing, "ROWS_A_BUCKET", 64)
    s = spark.createDataFrame([(0, "a", 6000, 6000.0), (1, "b", 2000, 2000.0), (2, "c", 1000, 2000.0)], "sid int, source string, source_size long, target double").withColumns({"rows": F.lit(1), "weight": F.lit(1.0)})
    slots = mixing.schedule(mixing.plan(s, 10)).orderBy("slot").collect()
    assert [r["slot"] for r in slots] == list(range(1000))
    seen, quota = Counter(), {0: 600, 1: 200, 2: 200}
    for i, r in enumerate(slots, 1):
        assert r["rank"] == seen[r["sid"]] and r["block"] == r["rank"] % {0: 600, 1: 200, 2: 100}[r["sid"]]
        seen[r["sid"]] += 1
        # every prefix holds each source in its share, but for a few slots
        assert all(abs(seen[k] - i * n / 1000) <= 4 for k, n in quota.items())
    assert seen == quota


def test_mix_is_what_its_slots_hold(docs, rows):
    from fsmeta.llm import mixing

    taken, first, n = Counter(), {}, Counter()
    for r in mixing.mixed(docs, block=16).collect():
        assert 0 <= r["lo"] < r["hi"]
        taken[r["doc_id"]] += r["hi"] - r["lo"]
        first[r["doc_id"]] = min(first.get(r["doc_id"], 1 << 60), r["slot"])
        n[r["doc_id"]] += 1
    for r in mixing.mix(docs, block=16).collect():
        if r["doc_id"] != 1:  # two equal rows
            assert (r["taken"], r["first_slot"], r["n_slots"]) == (taken[r["doc_id"]], first.get(r["doc_id"]), n[r["doc_id"]])
    assert sum(r["taken"] for r in mixing.mix(docs, block=16).collect()) == sum(taken.values())


def base_of(t):
    t = t or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    c, covered = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4)), set()
    for i in range(len(w) - 4):
        if c[tuple(w[i : i + 5])] > 1:
            covered.update(range(i, i + 5))
    return len(w), sum(map(len, w)), len(re.findall("[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered)


def test_quality_rules(spark, docs, none, rows):
    from fsmeta.llm import quality_rules as qr

    more = [(100 + i, t) for i, t in enumerate(["a b c d e " * 6, "a b c d e a b c d e", "x y\nx y\n\nx y", "a b c d e f a b c d e", "p q r s t u " * 3 + "v", "a a a a a a a", "1 2 3 4 5 6 7 8 9 10 11"])]
    d = spark.createDataFrame([(k, t) for k, t, *_ in rows] + more, "doc_id long, text string")
    cols = ("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    got = qr.judge(d, d.filter("doc_id < 4").select("doc_id"))
    assert as_rows(got, *cols) == sorted(((k, *base_of(t)) for k, t in [(k, t) for k, t, *_ in rows] + more), key=repr)
    for r in got.collect():
        assert r["base_failed"] == (r["n_words"] < 10 or 100 * r["n_repeat_words"] > 20 * r["n_words"]) and not (r["base_failed"] and r["kept"])
    assert qr.judge(none, none.select("doc_id")).count() == 0
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_log_ratios_match_counts(spark):
    from fsmeta.llm import quality_rules as qr

    d = spark.createDataFrame([(1, "a b a"), (2, "c ### d"), (3, None)], "doc_id long, text string")
    lr = {r["bucket"]: r["lr"] for r in qr.log_ratios(d, d.filter("doc_id = 1").select("doc_id"), buckets=64).collect()}
    g = {r["doc_id"]: r["g"] for r in d.select("doc_id", qr.grams(F.coalesce("text", F.lit("")), 64).alias("g")).collect()}
    raw, good = Counter(g[1] + g[2] + g[3]), Counter(g[1])
    want = {b: np.log((good[b] + 1) / (len(g[1]) + 64)) - np.log((raw[b] + 1) / (sum(raw.values()) + 64)) for b in range(64)}
    assert len(lr) == 64 and all(abs(lr[b] - want[b]) < 1e-12 for b in range(64))


def sets_by_hand(t, span=5):
    w = WORD.findall((t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
    return frozenset(tuple(w[i : i + span]) for i in range(len(w) - span + 1)) if len(w) >= span else frozenset([tuple(w)] if w else [])


def components_by_hand(pairs, percent=75):
    s = [(k, sets_by_hand(t)) for k, t in pairs]
    up = list(range(len(s)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for i in range(len(s)):
        for j in range(i):
            n = len(s[i][1] & s[j][1])
            if n and 100 * n >= percent * (len(s[i][1]) + len(s[j][1]) - n):
                up[root(i)] = root(j)
    least = {}
    for i, (k, _) in enumerate(s):
        if k is not None:
            least[root(i)] = min(k, least.get(root(i), k))
    return sorted(((k, len(x), least.get(root(i), None) if x else k) for i, (k, x) in enumerate(s)), key=repr)


def test_jaccard_join(docs, none, rows):
    from fsmeta.llm.jaccard_join import join_components

    assert as_rows(join_components(docs), "doc_id", "n_shingles", "component_id") == components_by_hand([(k, t) for k, t, *_ in rows])
    assert join_components(none).count() == 0


def variants(n, seed=3):
    rng = np.random.default_rng(seed)
    base, out = text_of(20, 80).split(), []
    for i in range(n):
        w = list(base)
        for at in rng.integers(0, len(w), int(rng.integers(0, 8))):
            w[at] = f"v{int(rng.integers(40))}"
        out.append((i, " ".join(w) + (" shared passage " + text_of(21, 30) if i % 7 == 0 else "")))
    return out + [(1000 + i, text_of(300 + i, 40) + " " + text_of(22, 60)) for i in range(20)]


@pytest.mark.parametrize("leaf,shrink,pivots,listed,part", [(48, 0.9, 16, 2_000_000, 512), (3, 20.0, 4, 2_000_000, 7), (0, 0.0, 3, 5, 3)])
def test_jaccard_join_near_copies(spark, monkeypatch, leaf, shrink, pivots, listed, part):
    from fsmeta.llm import jaccard_join as jj

    for name, v in (("LEAF", leaf), ("CELL", leaf), ("BLOCK", 16), ("SHRINK", shrink), ("PIVOTS", pivots), ("LISTED", listed), ("PART", part), ("PIECE", 900), ("LEVELS", 2)):
        monkeypatch.setattr(jj, name, v)
    pairs = variants(60)
    d = spark.createDataFrame(pairs, "doc_id long, text string").repartition(4)
    assert as_rows(jj.join_components(d), "doc_id", "n_shingles", "component_id") == components_by_hand(pairs)


@pytest.mark.parametrize("percent", [50, 90, 95])
def test_jaccard_join_thresholds(spark, percent):
    from fsmeta.llm import jaccard_join as jj

    words = text_of(40, 80).split()
    pairs = [(i, " ".join(words[:n])) for i, n in enumerate(range(5, 80, 3))] + [(100 + i, " ".join(words[i:])) for i in range(0, 60, 7)] + [(200, " ".join(words[:14])), (201, " ".join(words[:13]))] + variants(12)
    pairs = [(1000 * (k >= 1000) + i, t) for i, (k, t) in enumerate(pairs)]
    d = spark.createDataFrame(pairs, "doc_id long, text string").repartition(3)
    assert as_rows(jj.join_components(d, percent=percent), "doc_id", "n_shingles", "component_id") == components_by_hand(pairs, percent)


def test_first_shingles_suffice():
    """Whatever the sizes of two partners, each finds as many shared first shingles as it needs."""
    from fsmeta.llm.jaccard_join import needed, overlap, shipped

    for percent in range(5, 101, 5):
        for n in range(1, 120):
            assert 1 <= shipped(n, percent) <= overlap(n, percent) <= n
            for m in range(overlap(n, percent), n + 1):
                both = min(shipped(n, percent), shipped(m, percent))
                assert needed(n, percent) <= both and needed(m, percent) <= both


def repeats_by_hand(texts, length):
    c = Counter(b[i : i + length] for b in texts for i in range(len(b) - length + 1))
    out = []
    for b in texts:
        gone = np.zeros(len(b) + 1, bool)
        for i in range(len(b) - length + 1):
            if c[b[i : i + length]] > 1:
                gone[i : i + length] = True
        runs = int((np.diff(np.concatenate([[0], gone.view(np.int8)])) == 1).sum())
        kept = bytes(x for x, g in zip(b, gone, strict=False) if not g)
        out.append((len(b), int(gone.sum()), runs, hashlib.sha256(kept).hexdigest()))
    return out


@pytest.mark.parametrize("length,listed,span_bytes,piece,crowd", [(200, 10**6, 10**8, 1 << 19, 10**5), (200, 0, 0, 1000, 0), (40, 10**6, 0, 300, 2), (7, 0, 10**8, 100, 10**5)])
def test_suffix_dedup(spark, docs, none, rows, monkeypatch, length, listed, span_bytes, piece, crowd):
    from fsmeta.llm import suffix_dedup as sd

    monkeypatch.setattr(sd, "PIECE", piece)
    monkeypatch.setattr(sd, "CROWD", crowd)
    passage = text_of(30, 60)
    extra = [(200, "ab" * 300 + passage), (201, passage + " é" * 50), (202, "q" + passage[:150]), (203, passage[5:] + passage[5:])]
    every = [(k, t) for k, t, *_ in rows if k != 10 and k != 15] + extra
    d = spark.createDataFrame(every, "doc_id long, text string").repartition(3)
    want = sorted(((k, *w) for (k, _), w in zip(every, repeats_by_hand([(t or "").encode() for _, t in every], length), strict=True)), key=repr)
    got = sd.remove_repeats(d, length=length, listed=listed, span_bytes=span_bytes)
    assert as_rows(got, "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == want
    assert sd.remove_repeats(none, length=length).count() == 0


def test_quality_classifier(spark, docs, none):
    from fsmeta.llm import quality_classifier as qc

    rng = np.random.default_rng(4)
    good = [(i, text_of(500 + i, int(rng.integers(20, 200))), 1) for i in range(80)]
    bad = [(100 + i, " ".join(w + "###" for w in text_of(700 + i, int(rng.integers(20, 200))).split()), 0) for i in range(40)] + [(150 + i, "BUY!! NOW!! " * 20, 0) for i in range(20)]
    d = spark.createDataFrame([r[:2] for r in good + bad], "doc_id long, text string")
    lab = spark.createDataFrame([(r[0], r[2]) for r in good + bad] + [(None, 1), (3, None), (999, 1)], "doc_id long, quality int")
    m = qc.fit(d, lab, F.col("k") % 5 != 0)
    held = [r for r in qc.score(d, m).collect() if r["doc_id"] % 5 == 0]
    assert np.mean([(r["score"] >= 0.3) == (r["doc_id"] < 100) for r in held]) > 0.95
    again = qc.score(docs, m, name="_q").collect()
    assert len(again) == 16 and all(0 <= r["_q"] <= 1 for r in again)
    flat = qc.fit(none, lab, F.lit(True))
    assert flat.good is None and {r["score"] for r in qc.score(docs.drop("score"), flat).collect()} == {0.5}
    assert qc.score(none.drop("score"), m).count() == 0


def test_components(spark):
    from fsmeta.llm.components import components

    chain = [(i, i + 1) for i in range(50)] + [(100, 101), (7, 7), (200, 100)]
    got = {r["node"]: r["label"] for r in components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(51)) and got[200] == got[101] == got[100] == 100
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
