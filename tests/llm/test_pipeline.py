"""The pipeline's stages in a row, each against what its input says it must do."""

import re
from collections import Counter

from pyspark.sql import functions as F

WORD = re.compile("[^\x20\x09-\x0d]+")


def test_stages(spark, sf):
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    seen = {}
    for name, stage in cp.STAGES:
        before = {r["doc_id"]: r for r in docs.collect()}
        out = stage(spark, docs, sf)
        if name != cp.STAGES[-1][0]:
            assert out.columns == columns
            out = cp.workspace.store(out, name)
        seen[name] = (before, out.collect())
        docs = out
    before, kept = seen["quality_classifier"]
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    good = [k for k in before if labels.get(k) == 1]
    assert sum(r["doc_id"] in good for r in kept) >= 0.97 * len(good)
    before, kept = seen["jaccard_join"]
    texts = Counter(r["text"] for r in kept)
    assert max(texts.values()) == 1 and {r["text"] for r in kept} <= {r["text"] for r in before.values()}
    from fsmeta.llm.jaccard_join import join_components

    d = spark.createDataFrame([tuple(r) for r in before.values()], docs.sparkSession.read.parquet(f"{sf}/documents.parquet").schema)
    assert sorted(r["doc_id"] for r in kept) == sorted(r[0] for r in join_components(d).filter("doc_id = component_id").select("doc_id").collect())
    before, kept = seen["decontamination"]
    norm = lambda t: re.sub(r"[\W_]+", " ", t.lower()).strip()
    items = [norm(r["text"]) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    dirty = {k for k, r in before.items() if any(i in norm(r["text"]) for i in items)}
    assert {r["doc_id"] for r in kept} == set(before) - dirty
    before, kept = seen["mixing"]
    total = sum(len(WORD.findall(r["text"])) for r in before.values())
    assert abs(sum(len(WORD.findall(r["text"])) for r in kept) - 1.5 * total) < 0.1 * total
    assert max(Counter(r["doc_id"] for r in kept).values()) <= 2
    before, kept = seen["token_output"]
    kept.sort(key=lambda r: r["start"])
    assert [r["doc_id"] for r in kept] == sorted(r["doc_id"] for r in kept) and kept[0]["start"] == 0


def test_registered_queries_run(spark, sf):
    from fsmeta.llm import queries

    names = set(queries.queries())
    assert {n.split("_")[0] for n in names} == {f"op{i}" for i in range(1, 11)}
    docs = spark.read.parquet(f"{sf}/documents.parquet").count()
    for name, q in queries.queries().items():
        n = q(spark, sf).count()
        assert n == docs or name.startswith(("op2_", "op4_")), name


def test_held_out_accuracy(spark):
    from fsmeta.llm import queries

    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang")
    lang = queries.op1_language_id(spark, sf).join(docs, "doc_id").filter("held_out")
    assert lang.agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    q = queries.op10_quality_classifier(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").filter("held_out")
    assert q.agg(F.avg((F.col("quality") == F.col("predicted")).cast("int"))).first()[0] > 0.95


def test_stages_take_odd_rows(spark, sf):
    """Null keys, repeated ids, null, empty and very long texts, null sources; and an empty table."""
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rest = [f.name for f in docs.schema.fields if f.name not in ("doc_id", "text", "source")]
    some = docs.limit(60).collect()
    row = lambda k, t, s: tuple({"doc_id": k, "text": t, "source": s}.get(f.name, some[0][f.name]) for f in docs.schema.fields)
    long = " ".join(r["text"] or "" for r in some) * 40
    odd = [row(None, some[1]["text"], "a"), row(None, None, None), row(some[2]["doc_id"], some[3]["text"], None), row(some[2]["doc_id"], some[2]["text"], some[2]["source"]), row(10**9, "", "b"), row(10**9 + 1, long, "b"), row(10**9 + 1, long, "b")]
    assert rest
    table = spark.createDataFrame([tuple(r) for r in some] + odd, docs.schema)
    for make in (table, table.limit(0)):
        now = cp.workspace.store(make, "odd")
        for name, stage in cp.STAGES:
            before = Counter((r["doc_id"], r["text"]) for r in now.select("doc_id", "text").collect()) if "text" in now.columns else None
            out = stage(spark, now, sf)
            if name == cp.STAGES[-1][0]:
                got = out.collect()
                assert Counter(r["doc_id"] for r in got) == Counter(k for (k, _), n in before.items() for _ in range(n))
                continue
            assert out.columns == docs.columns
            now = cp.workspace.store(out, name)
            after = Counter((r["doc_id"], r["text"]) for r in now.select("doc_id", "text").collect())
            assert set(after) <= set(before)
            if name == "jaccard_join" and make is table:
                assert max(after.values()) == 1
                assert {k for k in before if k[0] is None} <= set(after)  # rows without a key stay
            if name == "decontamination":
                assert {k for k in before if k[0] is None} <= set(after)
