import pytest
from pyspark.sql import functions as F

from depstrata.functions import aggregates as A
from depstrata.operators.counting import ROW
from depstrata.plans import features
from depstrata.plans.tree import SchemaTree, discover_many, join_trees, rank_solutions, same_rows
from depstrata.sources import save_tree
from tests.fixtures import purchases


@pytest.fixture(scope="module")
def table(spark):
    return purchases(spark)


@pytest.fixture(scope="module")
def tree(table):
    return SchemaTree.discover(table, D=3, seed=1)


def test_shape(tree, table):
    splits = {s.parent: set(s.children) for s in tree.splits}
    assert splits[ROW] == {"ord", "item"} and splits["ord"] == {"buyer", "day"}
    assert tree.leaves["channel"] == "ord" and tree.leaves["phone"] == "buyer" and tree.leaves["weight"] == "item"
    assert tree.stats()["depth"] == 3
    assert SchemaTree.from_json(tree.render("json")).signature() == tree.signature()
    assert "ord" in tree.render() and "->" in tree.render("dot")


def test_layers_join_to_the_table(tree, table, spark):
    layers = tree.decompose(table)
    assert {n: t.count() for n, t in layers.items()} == {ROW: 18, "ord": 8, "item": 5, "buyer": 4}
    assert same_rows(tree.recompose(layers), table)
    assert 0 < tree.compression(table) < 1
    assert tree.broken_edges(table) == []
    assert ("item", "price") in tree.broken_edges(purchases(spark, dirty=True))
    assert tree.to_df(spark).count() == 13 and tree.relations(spark).count() == 2 + len(tree.leaves)


def test_with_an_error_bound(spark):
    dirty = purchases(spark, dirty=True)
    approximate = SchemaTree.discover(dirty, D=2, eps=0.06, seed=1)
    assert set(approximate.split_of(ROW).children) == {"ord", "item"}
    assert set(SchemaTree.discover(dirty, D=3, seed=1).split_of(ROW).children) == {"ord", "item", "price"}
    least = SchemaTree.discover(dirty, D=3, eps=0.06, finder="min_error", seed=1)
    assert least.split_of(ROW).error == 0


def test_realisations(table):
    trees = discover_many(table.select("ord", "buyer", "day", "channel", "phone").distinct(), range(5), D=3)
    assert len(trees) >= 1
    assert rank_solutions(table, [("buyer", "day"), ("day", "ord")])[0] == ("day", "ord")


def test_set_aside_combinations_and_sinks(table, tmp_path):
    t = SchemaTree.discover(table, D=3, set_aside=["buyer"], split_combinations=True)
    assert "buyer" in t.leaves
    save_tree(t, str(tmp_path / "t.json"))
    assert SchemaTree.from_json((tmp_path / "t.json").read_text()).signature() == t.signature()


def test_combinations_are_nodes(spark):
    """a, b and c are a key; a and b together determine d and e, and d and e them, but neither does alone."""
    rows = [(a, b, c, (a + b) % 4, (a + 2 * b) % 4 + 4 * (a // 2), 10 * a + b) for a in range(4) for b in range(4) for c in range(3)]
    df = spark.createDataFrame(rows, "a int, b int, c int, d int, e int, f int")
    for seed in range(2):
        for on in (False, True):
            t = SchemaTree.discover(df, D=3, seed=seed, split_combinations=on)
            assert same_rows(t.recompose(t.decompose(df)), df), (seed, on)
            assert SchemaTree.from_json(t.render("json")).signature() == t.signature()
            assert sorted([*t.leaves, *(c for s in t.splits for c in s.children)]) == sorted(df.columns)
    # Any two of x, y, p and q determine the other two: whichever two the key takes are a combination with a split.
    wide = spark.createDataFrame([(a, b, c, (a + b) % 7, (a + 2 * b) % 7) for a in range(7) for b in range(7) for c in range(2)], "x int, y int, z int, p int, q int")
    t = SchemaTree.discover(wide, D=3, seed=0, split_combinations=True)
    nodes = list(t.combinations)
    assert len(nodes) == 1 and set(t.combinations[nodes[0]]) == set(t.split_of(ROW).children) - {"z"}
    assert set(t.split_of(nodes[0]).children) == {"x", "y", "p", "q"} - set(t.combinations[nodes[0]])
    for n in nodes:
        assert t.split_of(n) and t.parent(n) == ROW and n in t.render() and n in t.render("dot") and n in t.layers()
        assert t.broken_edges(wide) == []
    assert same_rows(t.recompose(t.decompose(wide)), wide.select(*t.columns))
    assert t.to_df(spark).where("kind = 'combination'").count() == len(nodes) and t.relations(spark).count() > 0


def test_twins_hang_on_one_of_them(spark, table):
    twin = table.withColumn("buyer_no", F.concat(F.lit("n"), "buyer")).withColumn("day_no", F.hash("day"))
    t = SchemaTree.discover(twin, D=3, seed=1)
    assert t.leaves["buyer_no"] == "buyer" and t.leaves["day_no"] == "day"
    assert {s.parent: set(s.children) for s in t.splits} == {ROW: {"ord", "item"}, "ord": {"buyer", "day"}}
    assert same_rows(t.recompose(t.decompose(twin)), twin)


def test_degenerate_tables(spark):
    one = SchemaTree.discover(spark.createDataFrame([(1, None)], "a int, b string"))
    assert set(one.columns) == {"a", "b"}
    empty = SchemaTree.discover(spark.createDataFrame([], "a int, b string"))
    assert empty.stats()["nodes"] == 3
    cycle = SchemaTree.discover(spark.createDataFrame([(i, i + 1, i + 2) for i in range(5)], "a int, b int, c int"))
    assert sorted([*cycle.leaves, *cycle.skeleton[1:]]) == ["a", "b", "c"]


def test_paths(tree, table):
    path = features.aggregation_path(tree, "price", "buyer")
    assert path.levels == ("item", "ord", "buyer") and path.through_root
    simple = features.simplify_path(table, path)
    assert simple.levels == ("ord", "buyer")
    assert features.subpaths(simple) == [("ord", "buyer"), ("buyer",)]
    assert features.relation_kind(tree, "buyer", "phone") == "one-to-one"
    assert features.relation_kind(tree, "buyer", "price") == "one-to-many"


def test_features(tree, table):
    got = {r.buyer: r for r in features.build_features(table, tree, "buyer", ["price", "phone", "channel"]).collect()}
    assert {b: r["price__mean@ord__max@buyer"] for b, r in got.items()} == {"b1": 15, "b2": 13, "b3": 15, "b4": 15}
    assert {b: round(r["price__std@buyer"], 4) for b, r in got.items()} == {"b1": 2.0, "b2": 2.1909, "b3": 1.7889, "b4": 2.3094}
    assert got["b2"].phone == "555-02"
    flat = features.shallow_features(table, "buyer", ["price"])
    assert {r.buyer: r["price__max@buyer"] for r in flat.collect()} == {b: r["price__max@buyer"] for b, r in got.items()}


def test_grain(tree, table):
    web = A.FeatureFunction("web", "categorical", lambda c: F.avg(F.when(c == "web", 1.0).otherwise(0.0)))
    path = features.simplify_path(table, features.aggregation_path(tree, "channel", "buyer"))
    share = lambda g: {r.buyer: r[1] for r in features.path_features(table, features.Path("channel", ("buyer",), False), [web], g).collect()}
    assert path.levels[-1] == "buyer"
    assert share("row") == {"b1": 1.0, "b2": 0.6, "b3": 0.4, "b4": 0.5}
    by_order = table.select("ord", "buyer", "channel").distinct()
    got = {r.buyer: r[1] for r in features.path_features(by_order, features.Path("channel", ("buyer",), True), [web], "row").collect()}
    assert got == {"b1": 1.0, "b2": 0.5, "b3": 0.5, "b4": 0.5}


def test_functions(spark):
    df = spark.createDataFrame([("a", 1.0, "x"), ("a", 3.0, None), ("a", None, "x"), ("b", 2.0, None)], "k string, v double, c string")
    fs = [A.interval_probability(0, 2), A.quantile(0.5), A.quantile(0.5, exact=False)]
    out = {r.k: r for r in df.groupBy("k").agg(*[f.build(F.col("v")).alias(f"f{i}") for i, f in enumerate(fs)], A.n_distinct().build(F.col("c")).alias("d"), A.n_distinct("value").build(F.col("c")).alias("dv")).collect()}
    assert (out["a"].f0, out["a"].f1, out["a"].d, out["a"].dv, out["b"].d, out["b"].dv) == (0.5, 2.0, 1, 2, 0, 1)


def test_surroundings(spark, table):
    left = spark.createDataFrame([("a", 5), ("a", 1), ("b", 9)], "k string, t int")
    right = spark.createDataFrame([("a", 2, 7.0), ("a", 5, 8.0)], "k string, t int, v double")
    got = {(r.k, r.t): r.last_v for r in features.asof(left, right, "k", "t", "v").collect()}
    assert got == {("a", 5): 8.0, ("a", 1): None, ("b", 9): None}
    buyers = table.select("buyer", "phone").distinct()
    none = SchemaTree(("buyer", "phone"))
    assert join_trees({"p": (table, none), "b": (buyers, none)}, [("p", "buyer", "b", "buyer"), ("p", "buyer", "b", "phone")]) == [("p.buyer", "b.buyer")]
