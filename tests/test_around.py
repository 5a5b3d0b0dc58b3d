"""Sources, sinks, applications, functions, streams, entry points."""

import importlib
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from topfd.functions import udx
from topfd.model import Relation
from topfd.operators import apply as A
from topfd.plans.search import discover
from topfd.sources import files, views
from topfd.streaming import monitor

ROWS = [(1, "a", "x"), (2, "a", "x"), (3, "b", "y"), (4, None, "z"), (5, None, "z"), (6, "c", None)]


@pytest.fixture
def df(spark):
    return spark.createDataFrame(ROWS, "id int, l string, r string")


def test_split_and_join_back(df):
    assert tuple(A.check_lossless(df, ["l"], ["r"]).first()) == (0, 0)
    broken = df.union(df.sparkSession.createDataFrame([(7, "a", "other")], df.schema))
    lost, made = A.check_lossless(broken, ["l"], ["r"]).first()
    assert lost == 0 and made == 3
    assert tuple(A.storage_saving(df, ["l"], ["r"]).first()) == (6, 4, 18, 12 + 8, -2)


def test_violations(df, spark):
    assert A.violating_classes(df, ["l"], "r").count() == 0
    broken = df.union(spark.createDataFrame([(7, None, None), (8, "b", "y")], df.schema))
    assert [tuple(r) for r in A.violating_classes(broken, ["l"], "r").collect()] == [(None, 2, 3, 1)]
    assert sorted(r["id"] for r in A.violating_rows(broken, ["l"], "r").collect()) == [4, 5, 7]
    assert tuple(A.violation_summary(broken, ["l"], "r").first()) == (4, 1, 3)


def test_files_round_trip(df, spark, tmp_path):
    for kind in ("parquet", "orc", "json", "csv"):
        (df.write.option("header", True) if kind == "csv" else df.write).format(kind).save(f"{tmp_path}/{kind}")
        rel = files.relation(spark, f"{tmp_path}/{kind}", kind, ["l", "r"])
        assert [(rel.lhs_text(f.lhs), rel.columns[f.rhs], f.redundancy) for f in discover(rel, 5).fds] == [("l", "r", 2), ("r", "l", 2)]
    with pytest.raises(ValueError):
        files.relation(spark, "x", "nope")


def test_results_and_evidence_are_stored(df, spark, tmp_path):
    from topfd.operators import evidence

    found = discover(df, 5)
    files.save_result(found, f"{tmp_path}/r", "t")
    assert spark.read.parquet(f"{tmp_path}/r/answers").count() == len(found.fds)
    assert spark.read.parquet(f"{tmp_path}/r/stats").first()["relation"] == "t"
    evidence.save_evidence(found.rel, found.edges, f"{tmp_path}/e")
    again = evidence.load_evidence(found.rel, f"{tmp_path}/e")
    assert again == found.edges
    assert discover(df, 5, edges=again).fds == found.fds
    files.publish(found)
    assert spark.sql("SELECT max(card) FROM fd_cards").first()[0] == 6


def test_functions(spark):
    one = spark.createDataFrame([("a,b", "c"), ("", "d")], "lhs_text string, rhs string")
    text = one.select(udx.format_fd(F.col("lhs_text"), F.col("rhs")).alias("t"))
    assert [r["t"] for r in text.collect()] == ["{a,b}->c", "{}->d"]
    assert [(r["p"]["lhs"], r["p"]["rhs"]) for r in text.select(udx.parse_fd(F.col("t")).alias("p")).collect()] == [(["a", "b"], "c"), ([], "d")]
    udx.register(spark)
    one.createOrReplaceTempView("_one")
    assert sorted(map(str, (tuple(r) for r in spark.sql("SELECT e.* FROM _one, LATERAL fd_explode(lhs_text, rhs) e").collect()))) == sorted(["('a', 'c')", "('b', 'c')", "(None, 'd')"])


def _stream(spark, tmp_path, parts):
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, "k string, v string, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/{i}")
    schema = "k string, v string, ts timestamp"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")


def test_stream_finds_contradictions_and_resumes(spark, tmp_path):
    from datetime import datetime

    at = lambda h: datetime(2024, 1, 1, h)
    first = [("a", "1", at(1)), ("b", None, at(1)), ("a", "1", at(2))]
    second = [("a", "2", at(3)), ("b", None, at(3)), ("b", "x", at(4)), (None, "n", at(4))]
    events = _stream(spark, tmp_path, [first])
    monitor.drain(monitor.contradictions(events, ["k"], "v"), "_c1", f"{tmp_path}/cp")
    assert spark.table("_c1").count() == 0
    spark.createDataFrame(second, "k string, v string, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/1")
    out = f"{tmp_path}/out"
    q = monitor.contradictions(events, ["k"], "v").writeStream.format("parquet").option("checkpointLocation", f"{tmp_path}/cp2").trigger(availableNow=True).start(out)
    q.awaitTermination()
    got = sorted((r["lhs_key"], r["rhs_first"], r["rhs_now"]) for r in spark.read.parquet(out).collect())
    want = sorted((r["lhs_key"], r["rhs_first"], r["rhs_now"]) for r in monitor.contradictions_batch(spark.createDataFrame(first + second, "k string, v string, ts timestamp"), ["k"], "v").collect())
    assert got == want == [('{"k":"a"}', "1", "2"), ('{"k":"b"}', None, "x")]
    # a restart from the same checkpoint has nothing more to say
    q = monitor.contradictions(events, ["k"], "v").writeStream.format("parquet").option("checkpointLocation", f"{tmp_path}/cp2").trigger(availableNow=True).start(out)
    q.awaitTermination()
    assert spark.read.parquet(out).count() == 2


def test_drained_rows_are_files_and_go_on_from_their_checkpoint(spark, tmp_path):
    from datetime import datetime

    at = lambda h: datetime(2024, 1, 1, h)
    first = [("a", "2", at(1)), ("a", "1", at(1)), ("a", None, at(2)), ("b", "x", at(5)), ("b", "y", None), ("c", None, at(1)), ("c", "z", at(1))]
    events = _stream(spark, tmp_path, [first])
    found = monitor.drain(monitor.contradictions(events, ["k"], "v"), "_c2", f"{tmp_path}/cp")
    assert found.inputFiles()
    columns = ("lhs_key", "rhs_first", "rhs_now", "at")
    want = monitor.contradictions_batch(spark.createDataFrame(first, "k string, v string, ts timestamp"), ["k"], "v").select(*columns)
    assert sorted(map(str, found.select(*columns).collect())) == sorted(map(str, want.collect())) and want.count() == 4
    spark.createDataFrame([("b", "x", at(9)), ("b", "y", at(9))], "k string, v string, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/1")
    monitor.drain(monitor.contradictions(events, ["k"], "v"), "_c2", f"{tmp_path}/cp")
    assert spark.table("_c2").count() == 5


def test_first_arrivals_are_kept_in_files(spark, tmp_path):
    from datetime import datetime

    rows = [(str(i % 7), str(i), datetime(2024, 1, 1, i % 24)) for i in range(40)]
    events = _stream(spark, tmp_path, [rows])
    found = monitor.drain(monitor.distinct_events(events, ["k"], late="3650 days"), "_d", f"{tmp_path}/cp")
    assert found.inputFiles() and found.columns == ["k", "v", "ts"]
    assert sorted(r["k"] for r in found.collect()) == [str(i) for i in range(7)]


def test_first_arrivals_need_no_closing_batch(spark, tmp_path):
    from datetime import datetime
    from pathlib import Path

    batches = lambda name: len(list(Path(f"{tmp_path}/{name}/commits").glob("[0-9]*")))
    events = _stream(spark, tmp_path, [[(str(i % 7), str(i), datetime(2024, 1, 1, i % 24)) for i in range(40)]])
    first = monitor.distinct_events(events, ["k"], late="3650 days")
    before, found = spark.conf.get(monitor.CLOSING), {}
    for name, closing in (("with", True), ("without", False)):
        found[name] = monitor.drain(first, f"_{name}", f"{tmp_path}/{name}", closing=closing).select("k").collect()
        assert spark.conf.get(monitor.CLOSING) == before
    assert sorted(found["with"]) == sorted(found["without"]) and (batches("with"), batches("without")) == (2, 1)
    # what comes later goes on from there
    spark.createDataFrame([("3", "x", datetime(2024, 1, 2)), ("new", "x", datetime(2024, 1, 2))], "k string, v string, ts timestamp").coalesce(1).write.parquet(f"{tmp_path}/in/1")
    assert monitor.drain(first, "_without", f"{tmp_path}/without", closing=False).count() == 8


def test_windows_over_streams_and_tables(spark, tmp_path):
    from datetime import datetime

    rows = [("a", "1", datetime(2024, 1, 1, h)) for h in (1, 2, 9)] + [("b", "1", datetime(2024, 1, 2, 1))]
    table = spark.createDataFrame(rows, "k string, v string, ts timestamp")
    streamed = monitor.drain(monitor.class_sizes(_stream(spark, tmp_path, [rows]), ["k"]), "_w", f"{tmp_path}/cp", "complete")
    assert sorted(map(tuple, streamed.collect())) == sorted(map(tuple, monitor.class_sizes(table, ["k"]).collect()))
    assert monitor.class_sizes(table, ["k"], window="6 hours", slide="3 hours").count() > 4
    assert sorted(r["size"] for r in monitor.class_sizes(table, ["k"], gap="3 hours").collect()) == [1, 1, 2]
    assert monitor.distinct_events(table, ["k"]).count() == 2


def test_every_view_has_its_columns(spark):
    for name, view in views.VIEWS.items():
        assert set(views.COLUMNS[name]) <= set(view(spark, "/root/testdata/sf0.001").columns), name


def test_entry_and_registry(spark):
    entry = importlib.import_module("__spark_entry__")
    out = entry.entry(spark)
    assert out.count() == 10 and out.columns[:3] == ["rank", "lhs_text", "rhs"]
    names = entry.queries()
    assert len(names) > 100 and set(entry.oracle_sql()) <= set(names)


def test_rest_imports_without_the_llm_part():
    code = """
import sys
class Block:
    def find_spec(self, name, path=None, target=None):
        if name.startswith('topfd.llm') or name == 'corpus_pipeline':
            raise ModuleNotFoundError(name)
sys.meta_path.insert(0, Block())
import __spark_entry__ as e
assert not [q for q in e.queries() if q.startswith('op') or q == 'pipeline']
assert len(e.queries()) > 100 and e.oracle_sql()
"""
    subprocess.run([sys.executable, "-c", code], check=True, cwd=Path(__file__).parent.parent)


def test_prefix_keeps_ties(spark):
    df = spark.createDataFrame([(i // 2,) for i in range(20)], "k int")
    assert views.prefix(df, "k", 0.35).count() == 8 and views.prefix(df, "k", 1.0).count() == 20


def test_relation_over_a_subset(spark):
    rel = Relation.bind(views.read(spark, "/root/testdata/sf0.001", "customer"), ["c_nationkey", "c_mktsegment"])
    assert rel.m == 2 and discover(rel, 3).fds == []
