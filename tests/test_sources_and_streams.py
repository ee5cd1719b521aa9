from datetime import datetime, timedelta

import pytest

from subgraph_engine import graphs
from subgraph_engine.prepare import prepare
from subgraph_engine.sources import read_edge_list, read_edges, read_result, read_vertex_list, write_edge_list, write_result
from subgraph_engine.store import ROW, MemoryStore, ParquetStore
from subgraph_engine.streaming import events as ev


def test_edge_list_text(spark, tmp_path):
    (tmp_path / "g.e").write_text("# edges\n1 2 0.5\n\n  2\t3 1.5\n")
    (tmp_path / "g.v").write_text("1\n2\n3\n9\n")
    edges = read_edge_list(spark, str(tmp_path / "g.e"), weighted=True)
    assert [tuple(r) for r in edges.orderBy("src").collect()] == [(1, 2, 0.5), (2, 3, 1.5)]
    g = prepare("g", edges, weighted=True, vertices=read_vertex_list(spark, str(tmp_path / "g.v")))
    assert g.vertices.count() == 4
    write_edge_list(edges, str(tmp_path / "out"))
    assert sorted(map(tuple, read_edge_list(spark, str(tmp_path / "out"), True).collect())) == [(1, 2, 0.5), (2, 3, 1.5)]


def test_a_broken_line_is_an_error(spark, tmp_path):
    (tmp_path / "bad.e").write_text("1 two\n")
    with pytest.raises(Exception, match="CAST_INVALID_INPUT"):
        read_edge_list(spark, str(tmp_path / "bad.e")).collect()


@pytest.mark.parametrize("fmt", ["parquet", "json", "csv", "orc"])
def test_tabular_edges_and_results(spark, sf_dir, tmp_path, fmt):
    edges = graphs.geo(spark, sf_dir).edges
    edges.write.format(fmt).save(str(tmp_path / "e"))
    back = read_edges(spark, str(tmp_path / "e"), fmt)
    assert back.exceptAll(edges).count() == edges.exceptAll(back).count() == 0
    values = edges.selectExpr("src as vid", "dst as value")
    write_result(values, str(tmp_path / "r"), fmt)
    assert read_result(spark, str(tmp_path / "r"), fmt).exceptAll(values).count() == 0
    write_result(values, "", "noop")


@pytest.mark.parametrize("kind", ["parquet", "memory"])
def test_stores(spark, tmp_path, kind):
    store = ParquetStore(spark, str(tmp_path)) if kind == "parquet" else MemoryStore()
    row = lambda kind, wid, x: (kind, wid, x, 0, 1, [bytearray(b"a")])
    rows = spark.createDataFrame([row("partial", 0, 1), row("partial", 1, 2), row("messages", 1, 3)], ROW)
    store.put(0, rows.filter("wid = 0"), part=0)
    store.put(0, rows.filter("wid = 1"), part=1)
    store.put(1, rows.filter("kind = 'messages'"))
    assert store.get("partial", 0).count() == 2 and store.get("messages", 1).count() == 1 and store.get("partial", 1).count() == 0
    assert [tuple(r)[:5] for r in store.get("partial", 0, [1]).collect()] == [("partial", 1, 2, 0, 1)]
    store.put(0, rows.filter("wid = 0"), part=1)  # a part that is written again takes the place of the first
    assert sorted(r.wid for r in store.get("partial", 0).collect()) == [0, 0]
    store.drop(0)
    with pytest.raises(ValueError):
        store.get("other", 1)


def _events(spark, days):
    start = datetime(2024, 1, 1, 12)
    return spark.createDataFrame([(k, start + timedelta(days=d), 1, "click", 1.0, "{}") for k, d in enumerate(days)], ev.EVENT)


def test_late_rows_are_dropped(spark, tmp_path):
    folder = str(tmp_path / "in")
    for days in ([0, 1, 10], [11, 20], [0, 21, 40]):  # the last file's day 0 comes when day 8 is settled
        _events(spark, days).coalesce(1).write.mode("append").parquet(folder)
    rows = ev.tumbling(ev.event_stream(spark, folder, files_per_trigger=1), delay="2 days")
    got = {r.w.start.day: r.n for r in ev.run_to_end(spark, rows).collect() if r.w.start.month == 1}
    assert got == {1: 1, 2: 1, 11: 1, 12: 1, 21: 1, 22: 1}


def test_growing_components_follow_batches(spark):
    grow = ev.GrowingComponents(spark)
    for edges in ([(1, 2), (3, 4)], [(5, 6)], [(4, 5)], [(2, 6), (8, 8)]):
        grow.add(spark.createDataFrame(edges, "src long, dst long"))
    assert {r.vid: r.component for r in grow.labels.collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 1, 8: 8}
