"""Each stage against a plain version on its own input, and on the cases that no table has."""

import brute
import corpus_pipeline
import numpy as np
import pytest

from suffix_engine.llm import mixing, quality

SF = "/root/testdata/sf0.001"
STAGES = dict(corpus_pipeline.STAGES)


def rows_of(df):
    return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]


def test_stages(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    columns = docs.columns
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(str(tmp_path / name))
        out = spark.read.parquet(str(tmp_path / name))
        before = rows_of(docs)
        if name == "quality":
            scores = {r.doc_id: r.score for r in quality.quality_scores(docs, labels).collect()}
            assert sorted(rows_of(out)) == sorted((d, t) for d, t in before if scores[d] >= 0.5)
        elif name == "lines":
            want = brute.lines(before)
            assert {d: brute.sha(t) for d, t in rows_of(out)} == {d: w[2] for d, w in want.items()}
            assert all(r.n_chars == len(r.text) for r in out.collect())
        elif name == "near_duplicates":
            want = brute.jaccard_components(before, 5, 80)
            assert sorted(rows_of(out)) == sorted((d, t) for d, t in before if want[d][1] == d)
        elif name == "decontamination":
            items = [(r.item_id, r.text) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
            want = brute.contaminated(before, items)
            assert sorted(rows_of(out)) == sorted((d, t) for d, t in before if not want[d][4])
        else:
            rates = {r.doc_id: r.rate for r in mixing.mixing_rates(docs, labels).collect()}
            assert sorted(rows_of(out)) == sorted(before) and {r.doc_id: r.rate for r in out.collect()} == pytest.approx(rates)
            of = lambda where: [rates[r.doc_id] for r in labels.where(where).collect() if r.doc_id in rates]
            clean, toxic = of("quality = 1 and toxic = 0"), of("toxic = 1")
            assert np.median(clean) > 0.8 and np.mean(clean) > 2 * np.mean(toxic)
            assert out.columns == [*columns, "n_tokens", "rate"]
        if name != "mixing":
            assert out.columns == columns
        kept[name] = out.count()
        docs = out
    assert corpus_pipeline.run(spark, SF).count() == kept["mixing"] > 50


ODD = "doc_id long, text string, lang string, source string, n_chars long, _key string, _n int, score string, block int"


@pytest.mark.parametrize("name", STAGES)
def test_stages_with_odd_rows(spark, name):
    long = " ".join(f"w{i % 997}" for i in range(120_000))
    rows = [(1, "a b c d e f g", "en", None, 13, "k", 1, "s", 2)] * 2 + [(None, None) + (None,) * 7, (None, "") + (None,) * 7, (4, long, None, "x", None, None, None, None, None), (None, long) + (None,) * 7]
    docs = spark.createDataFrame(rows, ODD)
    out = STAGES[name](spark, docs, SF)
    assert out.columns[: len(docs.columns)] == docs.columns
    got = out.collect()
    assert len(got) <= len(rows) and STAGES[name](spark, docs.limit(0), SF).collect() == []
    if name in ("lines", "decontamination"):
        assert len(got) == len(rows)
    if name == "near_duplicates":
        assert sorted((r.doc_id or 0, (r.text or "")[:3]) for r in got) == [(0, ""), (0, ""), (1, "a b"), (4, "w0 ")]


def test_one_row_of_each_group_stays(spark):
    text = "one two three four five six seven eight"
    rows = [(1, text), (1, text), (None, text), (2, text), (None, "x y"), (None, "x y"), (5, "p q r s t u v"), (5, "another text under that id is kept")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id or 0, r.text) for r in corpus_pipeline.one_of_each_group(spark, docs, SF).collect())
    assert got == [(0, "x y"), (1, text), (5, "another text under that id is kept"), (5, "p q r s t u v")]
