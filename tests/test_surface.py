"""Sources, sinks, SQL functions, plans and streams."""

import pytest
from pyspark.sql import functions as F

from suffix_engine.functions import sql
from suffix_engine.operators import bucketed, bwt, corpus, doubling, workloads
from suffix_engine.plans import lint
from suffix_engine.sources import text as sources
from suffix_engine.streaming import live

SF = "/root/testdata/sf0.001"


def test_lines_and_records(spark, tmp_path):
    (tmp_path / "a.txt").write_text(">one\nACGT\nAC\n\n>two\nGG\n")
    lines = sources.read_lines(spark, str(tmp_path / "a.txt")).orderBy("line").collect()
    assert [r.text for r in lines] == [">one", "ACGT", "AC", "", ">two", "GG"]
    got = {r.name: r.text for r in sources.read_fasta(spark, str(tmp_path / "a.txt")).collect()}
    assert got == {"one": "ACGTAC", "two": "GG"}
    spark.dataSource.register(sources.ByteRangeSource)
    ranges = spark.read.format("byte_ranges").option("path", str(tmp_path / "a.txt")).option("size", "5").load()
    assert bytes(r.byte for r in sources.rows_of_blocks(ranges).orderBy("pos").collect()) == (tmp_path / "a.txt").read_bytes()


def test_formats_and_sinks(spark, tmp_path):
    rows = spark.createDataFrame([(1, "a"), (2, "b")], "k long, t string")
    for kind in ("json", "csv", "orc", "parquet"):
        rows.write.format(kind).option("header", True).save(str(tmp_path / kind))
        assert sources.read_table(spark, str(tmp_path / kind), kind, "k long, t string", ["t"]).count() == 2
    c = corpus.literal(spark, "BANANA" * 20)
    t = bucketed.build(c).select("rank", "code")
    sources.write_sorted(t, str(tmp_path / "sorted"), files=3)
    assert spark.read.parquet(str(tmp_path / "sorted")).exceptAll(t).count() == 0
    sources.write_symbols(t, c, str(tmp_path / "symbols"), 50)
    assert "".join(r.symbols for r in spark.read.json(str(tmp_path / "symbols")).orderBy("block").collect()) == bwt.encode("BANANA" * 20)[0]


def test_sql_functions(spark):
    sql.register(spark)
    spark.createDataFrame([(1, "BANANA"), (2, None), (3, "")], "k long, t string").createOrReplaceTempView("words")
    rows = spark.sql("SELECT k, e.bwt, e.primary, bwt_decode(e.bwt, e.primary) AS t, r FROM (SELECT k, bwt_encode(t) AS e, bwt_runs(t) AS r FROM words) ORDER BY k").collect()
    assert [tuple(r) for r in rows] == [(1, "ANNB$AA", 4, "BANANA", 5), (2, None, None, None, None), (3, "$", 0, "", 1)]
    assert spark.sql("SELECT bwt_run_ratio(t) AS r FROM words").first().r == 8 / 6
    assert [tuple(r) for r in spark.sql("SELECT * FROM suffixes('CAT', 3) ORDER BY pos").collect()] == [(0, "CAT"), (1, "AT$"), (2, "T$$"), (3, "$$$")]


def test_plans(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    plan = docs.where("doc_id < 40").select("text")
    assert any("doc_id" in f for f in lint.pushed_filters(plan)) and all("lang" not in c for c in lint.read_columns(plan))
    c = workloads.items(spark, SF)
    first = doubling.init_ranks(c)
    for pairing, rerank in [("join", "group"), ("union_reduce", "group"), ("join", "distinct")]:
        df = doubling.one_round(first, 1, pairing, rerank)
        assert not lint.to_one_partition(df) and not lint.row_functions(df)
    bad = spark.range(10).selectExpr("id", "row_number() over (order by id) as r")
    assert lint.to_one_partition(bad)


def test_streams_equal_batches(spark, tmp_path):
    path = f"{SF}/events.parquet"
    batch = spark.read.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    events = live.read_events(spark, path)
    for window, slide in [("1 day", None), ("1 day", "6 hours")]:
        got = live.run_to_table(live.symbol_counts(events, window, slide))
        assert sorted(map(tuple, got.collect())) == sorted(map(tuple, live.symbol_counts(batch, window, slide).collect()))
    got = live.run_to_table(live.kmer_counts(events), "update").groupBy("user_id", "kmer").agg(F.sum("cnt")).collect()
    want = {}
    for r in workloads.event_sequences(spark, SF).collect():
        for i in range(len(r.text) - 2):
            want[r.user_id, r.text[i : i + 3]] = want.get((r.user_id, r.text[i : i + 3]), 0) + 1
    assert {(r[0], r[1]): r[2] for r in got} == want
    assert live.session_texts(batch).agg(F.sum(F.length("text"))).first()[0] == batch.count()
    docs = spark.readStream.schema("doc_id long, text string").parquet(f"{SF}/documents.parque[t]")
    live.index_documents(docs, str(tmp_path / "index")).awaitTermination()
    assert spark.read.parquet(str(tmp_path / "index")).count() == 200


def test_late_rows_are_dropped(spark, tmp_path):
    schema = "event_id long, ts timestamp, event_type string, user_id long"
    for i, day in enumerate(["2024-01-05", "2024-01-06", "2024-01-01", "2024-01-20"]):
        spark.createDataFrame([(i, day)], "event_id long, d string").selectExpr("event_id", "to_timestamp(d) as ts", "'view' as event_type", "1L as user_id").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        if i < 3:
            __import__("time").sleep(1.1)
    events = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = live.run_to_table(live.symbol_counts(events, "1 day", late="1 hour"), "append")
    assert sorted(str(r.start.date()) for r in got.collect()) == ["2024-01-05", "2024-01-06"]


@pytest.mark.parametrize("make,n", [(workloads.english, 316488), (workloads.dna, 376806), (workloads.proteins, 376806), (workloads.random_bases, None)])
def test_workload_sizes(spark, make, n):
    c = make(spark, SF)
    assert c.counts.sum() == c.n and (n is None or c.n == n)
