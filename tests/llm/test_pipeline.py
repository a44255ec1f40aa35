import re

from pyspark.sql import functions as F

import corpus_pipeline
from vecgraph.llm import entry
from vecgraph.llm.common import materialize, table


def shingle_set(t):
    w = re.findall(r"[a-z0-9\x80-\U0010ffff]+", t.lower())
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)}


def test_pipeline_equals_brute_force(spark, sf):
    rows = {r["doc_id"]: r["text"] for r in table(spark, sf, "documents").collect() if r["text"] and re.search(r"[^\W\d_]", r["text"])}
    keys = {i: [x.strip(" \t\n\x0b\x0c\r").lower() if x.isascii() else "".join(c.lower() if c.isascii() else c for c in x).strip(" \t\n\x0b\x0c\r") for x in t.split("\n")] for i, t in rows.items()}
    n: dict = {}
    for ks in keys.values():
        for k in set(ks):
            n[k] = n.get(k, 0) + 1
    rows = {i: "\n".join(x for x, k in zip(t.split("\n"), keys[i], strict=True) if not (k and n[k] >= 10)) for i, t in rows.items()}
    sets, kept = {i: shingle_set(t) for i, t in rows.items()}, []
    root = {i: i for i in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(rows)
    for a in ids:
        for b in ids:
            if b < a:
                c = len(sets[a] & sets[b])
                if c >= 0.8 * (len(sets[a]) + len(sets[b]) - c) - 1e-9:
                    x, y = find(a), find(b)
                    root[max(x, y)] = min(x, y)
    kept = {i for i in ids if find(i) == i}
    items = [shingle_set(r["text"]) for r in table(spark, sf, "benchmark").collect()]
    kept = {i for i in kept if not any(len(s & sets[i]) >= 0.8 * len(s) - 1e-9 for s in items)}
    got = corpus_pipeline.run(spark, sf)
    assert {r["doc_id"] for r in got.select("doc_id").distinct().collect()} == kept


def test_stages_take_empty_tables_and_other_columns(spark, sf):
    docs = table(spark, sf, "documents")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs.where("false"), sf).columns == docs.columns
        assert stage(spark, docs.where("false"), sf).count() == 0


def test_every_operator_has_its_query():
    assert sorted(int(re.match(r"op(\d+)_", n)[1]) for n in entry.QUERIES) == list(range(1, 11))


def test_stages_take_nulls_repeats_and_long_rows(spark, sf):
    docs = table(spark, sf, "documents")
    first = docs.where("text is not null").orderBy("doc_id").first().asDict()
    odd = [{**first, "doc_id": None}, {**first, "text": None}, {**first, "text": ""}, {**first, "source": None, "lang": None}, first, first, {**first, "doc_id": 10**9, "text": "unique words " + " ".join(f"x{i}y" for i in range(60_000))}]
    rows = docs.limit(50).unionByName(spark.createDataFrame(odd, docs.schema)).withColumns({c: F.lit("mine") for c in ("score", "lang_pred", "key", "n_lines", "row", "id", "g")})
    left = rows
    for name, stage in corpus_pipeline.STAGES[:-1]:
        left = materialize(stage(spark, left, sf), f"test-{name}")
        assert left.columns == rows.columns and left.where("score <> 'mine' or row <> 'mine'").count() == 0
        assert left.where(f"doc_id = {10**9}").count() == 1  # a clean document stays
    assert left.where(F.col("text").isNull()).count() == 0  # a null text has no language
    packed = corpus_pipeline.STAGES[-1][1](spark, left, sf)
    whole = packed.groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("t"), F.count_distinct("start").alias("pieces"), F.count("*").alias("rows"))
    assert whole.where("doc_id is not null and (n <> t or pieces <> rows)").count() == 0
    assert corpus_pipeline.STAGES[-1][1](spark, docs.where("false"), sf).count() == 0


def test_queries_run_on_the_smallest_tables(spark, sf):
    n = {t: table(spark, sf, t).count() for t in ("documents", "pages")}
    for name, rows in (("op3_line_dedup", n["documents"]), ("op7_language_id", n["documents"]), ("op9_warc", n["pages"]), ("op10_near_join", n["documents"]), ("op4_class_lm", n["documents"])):
        assert entry.QUERIES[name](spark, sf).count() == rows, name
    pieces = entry.QUERIES["op8_packing"](spark, sf)
    assert pieces.select("doc_id").distinct().count() == n["documents"]
    assert {c for c, _ in entry.QUERIES["op2_decontaminate"](spark, sf).dtypes} >= {"doc_id"}
