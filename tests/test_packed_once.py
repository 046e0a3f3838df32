"""A tree that is asked for in all modes is dealt out once."""

from pyspark.sql import DataFrame

from treeloom.engine import forests, metrics
from treeloom.sources import store
from treeloom.sources.trees import open_tree
from treeloom.workloads import measured


def test_all_modes_read_one_packed_table(spark, small, monkeypatch):
    """The forests were packed without markup first, and then again with it."""
    kept = dict(store._built)
    try:
        for key in [k for k in store._built if k[2] in ("market-forests", "market-markup")]:
            del store._built[key]
        made = []
        pack = forests._packed
        monkeypatch.setattr(forests, "_packed", lambda tree, spine, markup=False: made.append(markup) or pack(tree, spine, markup))
        monkeypatch.setattr(measured, "_W", ["w02"])
        asked = []
        monkeypatch.setattr(metrics, "timed", lambda run, runs: asked.append(run()) or 1.0)
        assert measured.measure_mode_times(spark, small).count() == 3
        assert made == [True] and len(asked) == 3
        n = asked[0].first()["n"]
        assert all(isinstance(x, DataFrame) for x in asked) and asked[1].count() == n and asked[2].select("pre").distinct().count() == n
        tree = open_tree(spark, small, "market")
        assert forests.packed(tree, []).inputFiles() == forests.packed(tree, [], markup=True).inputFiles()
    finally:
        store._built.clear()
        store._built.update(kept)
