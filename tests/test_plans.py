from codeprov.plans.inspect import inspect
from codeprov.queries import QUERIES
from codeprov.sources import files

SF = "/root/testdata/sf0.001"


def test_filters_and_columns_reach_the_scan(spark):
    p = inspect(QUERIES["O_filter"](spark, SF))
    assert any("l_quantity" in x and "l_shipdate" in x for x in p.pushed)
    assert not any("l_extendedprice" in c for c in p.columns)


def test_flagship_reads_two_columns_and_forms_no_product(spark):
    p = inspect(QUERIES["W01_clone_search"](spark, SF))
    assert not p.has("CartesianProduct", "BroadcastNestedLoopJoin") and not p.single_partition
    assert all("lang" not in c and "source" not in c for c in p.columns)


def test_fingerprints_need_no_exchange(spark):
    assert not inspect(QUERIES["W04_fingerprints"](spark, SF)).has("Exchange")


def test_asof_is_one_shuffle(spark):
    assert inspect(QUERIES["O_asof"](spark, SF)).nodes["Exchange"] == 1


def test_code_trees_and_sinks(spark, tmp_path):
    (tmp_path / "a").mkdir()
    (tmp_path / "a" / "x.sol").write_text("contract A { }")
    (tmp_path / "y.txt").write_text("no code")
    tree = files.code_tree(spark, str(tmp_path))
    assert [r.code for r in tree.collect()] == ["contract A { }"]
    df = spark.createDataFrame([(1, "a"), (2, "b"), (3, "a")], "id long, k string")
    files.save(df, str(tmp_path / "out"), by=["k"], sort=["id"])
    assert files.load(spark, str(tmp_path / "out"), schema=df.schema).exceptAll(df).count() == 0
