"""Queries on the lattice of customers cover all customers, not only a fixture's first 120."""

import pytest

from redgraph import queries
from redgraph.sources.tables import graph, read_table


class Asked(Exception):
    pass


@pytest.mark.parametrize("name", ["sssp_plain", "sssp_short_circuit", "sssp_bounded2", "widest_path", "update_curve_shape"])
def test_the_lattice_is_not_cut(monkeypatch, name):
    def asked(spark, sf_dir, kind, **options):
        if kind == "grid" or options:
            raise Asked(kind, options)

    monkeypatch.setattr(queries, "graph", asked)
    monkeypatch.setattr(queries.al, "sssp", lambda g, *a, **k: None)
    monkeypatch.setattr(queries.metrics, "update_curve", lambda r: None)
    monkeypatch.setattr(queries.metrics, "curve_shape", lambda r: type("Row", (), {"withColumn": lambda self, *a: self})())
    monkeypatch.setattr(queries.F, "lit", lambda x: x)
    with pytest.raises(Asked) as e:
        queries.QUERIES[name](None, "")
    assert e.value.args == ("grid", {})
    assert "c_custkey <" not in queries.ORACLES.get(name, "")


def test_every_customer_has_a_width(spark, sf):
    small = graph(spark, sf, "grid", first=120).ids().count()
    assert queries.QUERIES["widest_path"](spark, sf).count() == read_table(spark, sf, "customer").count() > small
