from pyspark.sql import functions as F

from hcube.operators import hast
from hcube.sources import datasource, store, udtf
from hcube.streaming import upkeep
from hcube.workloads import cubes


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_node_store_and_source(spark, sf, tmp_path):
    t = hast.tree(spark, cubes.C3, sf)
    store.write_nodes(t.nodes, str(tmp_path))
    back = store.read_nodes(spark, str(tmp_path), 2)
    assert rows(back[2].select("p_1", "p_2", "qty")) == rows(t.nodes[2].select("p_1", "p_2", "qty"))
    spark.dataSource.register(datasource.NodeSource)
    reader = spark.read.format("hcube").option("path", str(tmp_path)).option("height", 2).option("measures", "qty")
    df = reader.load()
    assert df.filter("depth = 1").agg(F.sum("qty")).first()[0] == t.nodes[0].first().qty
    assert df.count() == 1 + t.nodes[1].count() + t.nodes[2].count()
    assert reader.option("depth", 1).load().count() == t.nodes[1].count()
    assert store.register_views(t.nodes, {"flag": t.members("flag")}, "c3")[0] == "nodes_c3_2"
    assert spark.sql("SELECT sum(qty) FROM nodes_c3_1").first()[0] == t.nodes[0].first().qty


def test_formats(spark, sf, tmp_path):
    m = hast.tree(spark, cubes.C3, sf).members("flag").select("depth", "member_id", "label", "lo", "hi")
    for kind in ("csv", "json", "orc", "parquet"):
        assert rows(store.round_trip(m, str(tmp_path / kind), kind)) == rows(m)


def test_table_functions(spark):
    udtf.register(spark)
    got = spark.sql("SELECT count(*) FROM rst_cover(array(2L, 1L), array(5L, 3L), 8, 2)").first()[0]
    assert got == 6
    assert spark.sql("SELECT sum(n_descendants + 1) FROM louds_children('1101000', 0)").first()[0] == 3


def test_stream_upkeep(spark, sf, tmp_path):
    cube = cubes.C4.only("type", "time")
    raw = spark.read.parquet(f"{sf}/events.parquet")
    raw.repartition(3).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(raw.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    upkeep.maintain(stream, cube, str(tmp_path / "store"), str(tmp_path / "cp")).awaitTermination()
    for depth in range(4):
        want = upkeep.delta(upkeep.level_facts(raw, cube), cube, depth)
        assert rows(upkeep.read_sums(spark, cube, str(tmp_path / "store"), depth)) == rows(want)
    upkeep.compact(spark, cube, str(tmp_path / "store"), str(tmp_path / "small"))
    assert rows(upkeep.read_sums(spark, cube, str(tmp_path / "small"), 1)) == rows(upkeep.read_sums(spark, cube, str(tmp_path / "store"), 1))


def test_windows(spark, sf):
    raw = spark.read.parquet(f"{sf}/events.parquet")
    panes = upkeep.hourly(raw)
    two = upkeep.sliding_from_panes(panes, 2)
    assert two.agg(F.sum("cnt")).first()[0] == 2 * panes.agg(F.sum("cnt")).first()[0]
    assert upkeep.sessions(raw).agg(F.sum("cnt")).first()[0] == raw.count()
