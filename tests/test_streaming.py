from depstrata import sqlapi, streaming
from depstrata.plans.tree import SchemaTree
from tests.fixtures import purchases


def _files(spark, path, parts):
    for i, rows in enumerate(parts):
        spark.createDataFrame(rows, "user int, kind string, ts timestamp").coalesce(1).write.mode("append").parquet(path)


def _ts(h):
    from datetime import datetime, timedelta

    return datetime(2024, 1, 1) + timedelta(hours=h)


def test_monitor_dedupe_sessions(spark, tmp_path):
    path = str(tmp_path / "in")
    _files(spark, path, [[(1, "a", _ts(0)), (2, "b", _ts(1))], [(1, "c", _ts(2)), (2, "b", _ts(1))]])
    schema = "user int, kind string, ts timestamp"
    got = streaming.collected(streaming.monitor(streaming.replay(spark, path, schema), ["user"], ["kind"]), "t_monitor", "complete")
    assert [r.user for r in got.collect()] == [1]
    once = streaming.dedupe(streaming.with_watermark(streaming.replay(spark, path, schema)), ["user", "kind", "ts"])
    assert streaming.collected(once, "t_dedupe", "append").count() == 3
    static = spark.createDataFrame([(1, "x")], "id int, name string")
    assert streaming.collected(streaming.enrich(streaming.replay(spark, path, schema), static, "user", "id"), "t_join", "append").count() == 2


def test_late_rows_are_dropped(spark, tmp_path):
    path = str(tmp_path / "late")
    for rows in ([(1, "a", _ts(0)), (1, "b", _ts(30))], [(1, "z", _ts(72))], [(1, "late", _ts(1))], [(1, "z", _ts(120))]):
        _files(spark, path, [rows])
    stream = streaming.with_watermark(streaming.replay(spark, path, "user int, kind string, ts timestamp"))
    got = {r.start.day: r.n_rows for r in streaming.collected(streaming.windowed_error(stream, ["user"], ["kind"]), "t_windows", "append").collect()}
    assert got[1] == 1 and got[2] == 1


def test_batches(spark):
    tree = SchemaTree.discover(purchases(spark), D=3, seed=1)
    broken = set()
    check = streaming.revalidate(tree, [], broken)
    check(purchases(spark), 0)
    assert not broken
    check(purchases(spark, dirty=True), 1)
    assert ("item", "price") in broken
    across = set()
    dirty = purchases(spark, dirty=True).where("price = 12")
    streaming.revalidate(tree, [purchases(spark)], across)(dirty, 0)
    assert ("item", "price") in across
    states = []
    keep = streaming.sketch_state(states, [["ord"], ["ord", "item"]])
    keep(purchases(spark), 0)
    keep(purchases(spark), 1)
    assert streaming.estimates(states[0]) == [8, 18]


def test_sql_surface(spark):
    sqlapi.register(spark)
    assert spark.sql("select * from subpaths('ord > buyer')").count() == 2
    got = spark.sql("select * from return_probabilities('1,2,3')").collect()
    assert round(got[0].probability, 5) == 0.58333
    tree = SchemaTree.discover(purchases(spark), D=3, seed=1)
    assert spark.sql(f"select * from tree_nodes('{tree.render('json')}')").count() == 13
    sqlapi.views(tree.decompose(purchases(spark)) and {"v_items": tree.decompose(purchases(spark))["item"]})
    assert spark.sql("select * from v_items").count() == 5
