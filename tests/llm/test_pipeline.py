"""Each stage on what its predecessor kept, against plain versions."""

from pyspark.sql import functions as F

import corpus_pipeline as p
from topkpaths.llm import common, decontaminate, quality_crf, source_mix, token_orc

from .test_operators import awkward, brute_join


def test_stages(spark, sf):
    docs = common.table(spark, sf, "documents")
    names = docs.columns
    kept = [docs]
    for name, stage in p.STAGES:
        out = common.spill(stage(spark, kept[-1], sf), f"test-{name}")
        assert name == "tokens" or out.columns == names
        kept.append(out)
    rows = [k.collect() for k in kept]
    model = quality_crf.train(docs, common.table(spark, sf, "labels"))
    good = {r["doc_id"] for r in quality_crf.score(docs, model).where("score >= 0.3").collect()}
    assert {r["doc_id"] for r in rows[1]} == good
    low = {i: c for i, _, c in brute_join([(r["doc_id"], r["text"]) for r in rows[1]])}
    assert {r["doc_id"] for r in rows[2]} == {i for i, c in low.items() if i == c}
    bench = {r["item_id"]: r["text"] for r in common.table(spark, sf, "benchmark").collect()}
    hit = decontaminate.brute({r["doc_id"]: r["text"] for r in rows[2]}, bench)
    assert {r["doc_id"] for r in rows[3]} == {i for i, h in hit.items() if not h[-1]}
    times = {r["doc_id"]: r["repeats"] for r in source_mix.mix(kept[3]).collect()}
    assert len(rows[4]) == sum(times.values()) and {r["doc_id"] for r in rows[4]} == {i for i, n in times.items() if n}
    assert len(rows[5]) == len(rows[4])
    assert sum(r["n_tokens"] for r in rows[5]) == max(r["start"] + r["n_tokens"] for r in rows[5])
    assert token_orc.END_ID == 1 and p.run(spark, sf).count() == len(rows[5])


EXTRA = "row string, gram long, block int, key string, size int, place string, score double, repeats int, copy int, ranges int, quality int, component_id long"


def awkward_docs(spark):
    """Nulls in every column, empty, short and very long texts, repeated rows, copies, a passage of the benchmark, clashing columns."""
    long = " ".join(f"l{i % 977}x{i}" for i in range(250_000))  # longer than a slice of the scans
    secret = " ".join(f"s{i}" for i in range(12))
    texts = [*awkward(), (50, long), (51, long + " end"), (None, "held " + secret), (52, "held " + secret + " too"), (53, "#$%^ |||| " * 40)]
    rows = [(i, t, None if k % 3 == 0 else "en", None if k % 4 == 0 else f"s{k % 3}", None if k % 5 == 0 else 1, "x", 1, 2, None, 3, "p", 0.1, 9, 8, 7, 6, 5) for k, (i, t) in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, " + EXTRA).repartition(3), secret


def stored(spark, tmp_path, docs, secret):
    sf = str(tmp_path)
    docs.write.parquet(f"{sf}/documents.parquet")
    spark.createDataFrame([(8, 1, 0), (9, 1, None), (20, 1, 0), (53, 0, 1), (53, 0, 1), (7, None, 0), (None, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{sf}/labels.parquet")
    spark.createDataFrame([(None, secret), ("2", None), ("3", ""), ("4", "one")], "item_id string, text string").write.parquet(f"{sf}/benchmark.parquet")
    return sf


def plain_rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def test_stages_on_awkward_rows(spark, tmp_path):
    docs, secret = awkward_docs(spark)
    sf = stored(spark, tmp_path, docs, secret)
    docs = common.table(spark, sf, "documents")
    stages, rows = dict(p.STAGES), plain_rows(docs)
    for name, stage in p.STAGES[:-1]:
        assert stage(spark, docs, sf).columns == docs.columns, name

    model = quality_crf.train(docs, common.table(spark, sf, "labels"))
    numbered = spark.createDataFrame([(k, r[1]) for k, r in enumerate(rows)], "doc_id long, text string")
    good = {r["doc_id"] for r in quality_crf.score(numbered, model).where("score >= 0.3").collect()}
    assert plain_rows(stages["quality"](spark, docs, sf)) == [r for k, r in enumerate(rows) if k in good] and 0 < len(good) < len(rows)

    low = brute_join([r[:2] for r in rows])
    first = {i for i, _, c in low if i is not None and i == c}
    got = plain_rows(stages["near_duplicates"](spark, docs, sf))
    assert [r for r in got if r[0] is not None] == [r for r in rows if r[0] in first]
    assert all(r[0] is not None for r in got)  # both rows without an id are copies of documents

    bench = {k: t for k, t in enumerate([secret, None, "", "one"])}
    clean = [r for r in rows if not list(decontaminate.brute({0: r[1]}, bench).values())[0][-1]]
    assert plain_rows(stages["decontaminate"](spark, docs, sf)) == clean and len(clean) < len(rows) - 2

    times = sorted((r["doc_id"], r["size"], r["repeats"]) if r["doc_id"] is not None else (-1, r["size"], r["repeats"]) for r in source_mix.mix(docs).collect())
    assert len(plain_rows(stages["mix"](spark, docs, sf))) == sum(n for *_, n in times)

    index = sorted((r["start"], r["n_tokens"], r["doc_id"]) for r in stages["tokens"](spark, docs, sf).collect())
    assert len(index) == len(rows) and [i for *_, i in index] == sorted((r[0] for r in rows), key=lambda i: (i is not None, i))
    assert all(a + n == b for (a, n, _), (b, _, _) in zip(index, index[1:])) and {n for _, n, i in index if i in (0, 1)} == {1}
    assert p.run(spark, sf).count() > 0


def test_empty_tables_pass_all_stages(spark, tmp_path):
    docs, secret = awkward_docs(spark)
    sf = stored(spark, tmp_path, docs.where("false"), secret)
    assert p.run(spark, sf).collect() == []


def test_texts_go_to_the_workers_once(spark, sf, monkeypatch):
    """The two stages that judge whole rows send a row's text as part of the row alone; with several automata too, and whatever the case of the column's name."""
    docs = common.table(spark, sf, "documents").withColumnRenamed("text", "TEXT")
    model = quality_crf.train(docs, common.table(spark, sf, "labels"))
    kept, sent, kind = [], [], type(docs)
    with monkeypatch.context() as m:
        m.setattr(kind, "mapInArrow", lambda self, *a, f=kind.mapInArrow, **b: sent.append(self.columns) or f(self, *a, **b))
        for size in (decontaminate.MAX_ITEM_BYTES, 5_000):
            m.setattr(decontaminate.find, "__defaults__", (decontaminate.WINDOW, size, *decontaminate.find.__defaults__[2:]))
            kept.append(p.clean_of_benchmark(spark, docs, sf))
        kept.append(quality_crf.keep_good(docs, model))
    assert len(sent) == 4 and not [x for x in sent if "row" not in x or "text" in map(str.lower, x)]
    found = {r["doc_id"]: r["contaminated"] for r in decontaminate.op7_decontaminate(spark, sf).collect()}
    want = sorted(r[0] for r in docs.select("doc_id").collect() if not found[r[0]])
    assert sorted(r[0] for r in kept[0].select("doc_id").collect()) == sorted(r[0] for r in kept[1].select("doc_id").collect()) == want
    assert kept[2].columns == docs.columns
    good = {r["doc_id"] for r in quality_crf.score(docs, model).where(F.col("score") >= quality_crf.THRESHOLD).collect()}
    assert {r["doc_id"] for r in kept[2].select("doc_id").collect()} == good
