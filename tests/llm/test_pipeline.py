"""The stages on a small corpus with planted rows."""

import random

import corpus_pipeline
from netan.llm import ngram_join


def test_stages(spark, tmp_path):
    rng = random.Random(8)
    word = lambda: "".join(rng.choice(["th", "an", "er", "on", "in", "re"]) for _ in range(rng.randint(1, 4)))
    text = lambda n=80: " ".join(word() for _ in range(n))
    bench = [(k, text(30)) for k in range(3)]
    rows = [(k, text(), "en", f"src{k % 5}") for k in range(60)]
    rows += [(100, rows[0][1], "en", "src1"), (101, rows[1][1] + " more", "en", "src1"), (101, rows[1][1] + " more", "en", "src1")]  # copies
    rows += [(102, text(60) + " " + bench[1][1], "en", "src2"), (103, "short", "en", "src2"), (104, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").selectExpr("*", "length(text) AS n_chars")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"file://{tmp_path}/benchmark.parquet")
    docs.write.parquet(f"file://{tmp_path}/documents.parquet")
    at, columns, seen = docs, docs.columns, []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, f"file://{tmp_path}")
        assert at.columns == columns, name
        seen.append({r.doc_id for r in at.collect()})
    assert seen[0] == {*range(60), 100, 101, 102}
    assert seen[1] == {*range(60), 102}
    assert seen[2] == set(range(60))
    assert seen[3] <= seen[2]
    out = corpus_pipeline.run(spark, f"file://{tmp_path}").collect()
    assert {r.doc_id for r in out} == seen[3] and min(r.start for r in out) == 0
    assert sum(r.n_tokens for r in out) == max(r.start + r.n_tokens for r in out)


def test_odd_tables(spark, tmp_path):
    """Empty tables, clashing names, null and very long texts."""
    schema = "doc_id long, text string, lang string, source string, n_chars long, _gone_id long, _id string, _rid string, _x int, x int, rid string, component int, copies int, domain string"
    rng = random.Random(5)
    long_ = " ".join(rng.choice(["stone", "river", "cloud", "amber", "north"]) + str(rng.randint(0, 999)) for _ in range(60_000))
    more = (1, 7, "i", "r", 3, 4, "q", 5, 6, "d")
    rows = [(1, long_, "en", "src1", *more), (2, None, None, None, *more), (3, "", "en", "src1", *more), (None, long_ + " end", "en", None, *more)]
    bench = spark.createDataFrame([(1, "some words of a test that nobody has ever copied from anywhere at all")], "item_id long, text string")
    for name, part in (("some", rows), ("none", [])):
        at = f"file://{tmp_path}/{name}"
        bench.write.parquet(f"{at}/benchmark.parquet")
        spark.createDataFrame(part, schema).write.parquet(f"{at}/documents.parquet")
        docs = spark.read.parquet(f"{at}/documents.parquet")
        for stage, f in corpus_pipeline.STAGES[:-1]:
            docs = f(spark, docs, at)
            assert docs.columns == [c.split()[0] for c in schema.split(", ")], stage
        assert {r.doc_id for r in docs.collect()} <= {1, None}


def test_near_copies_at_five_words(spark, tmp_path):
    """Four of 200 words differ: 176 of 216 shingles of five words (0.81), but 181 of 213 of four words (0.8498)."""
    first = [f"w{k}" for k in range(200)]
    second = [f"x{k}" if k in (30, 70, 110, 150) else w for k, w in enumerate(first)]
    other = [f"x{k}" if k in (30, 60, 90, 120, 150) else w for k, w in enumerate(first)]  # 171 of 221: 0.77
    docs = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate((first, second, other))], "doc_id long, text string")
    assert {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, "").collect()} == {0, 2}


def test_routes_and_texts_are_dealt_once(spark, monkeypatch):
    """One exchange of routes on the way to the dealt keys, no table of them; one exchange of texts for both joins of the stage."""
    plans = {}

    def seen(df, name, kept=ngram_join.written):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return kept(df, name)

    monkeypatch.setattr(ngram_join, "written", seen)
    text = [" ".join(f"w{k}x{j}" for j in range(30)) for k in range(20)]
    rows = [(k, t) for k, t in enumerate(text)] + [(30, text[3]), (4, text[4]), (31, text[5] + " more")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    spark.conf.set("spark.sql.adaptive.autoBroadcastJoinThreshold", -1)
    try:
        out = corpus_pipeline.near_duplicates(spark, docs, "")
        assert sorted(r.doc_id for r in out.collect()) == list(range(20))
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.unset("spark.sql.adaptive.autoBroadcastJoinThreshold")
    assert "routes" not in plans and plans["dealt"].count("Exchange hashpartitioning") == 1
    final = out._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    dealt = [x for x in final.splitlines() if "Exchange hashpartitioning(xxhash64(doc_id" in x or "Exchange hashpartitioning(coalesce(doc_id" in x]
    assert sum("Reused" not in x for x in dealt) == 1, final
