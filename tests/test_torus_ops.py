import pytest
from micro import values

from sparkgraphs.model import catalog
from sparkgraphs.ops import queries as operators  # noqa: F401  (registers itself)
from sparkgraphs.queries import QUERIES, SQL


@pytest.mark.parametrize("name", ["op_torus_source", "op_udtf"])
def test_torus_arcs_come_of_the_parts(spark, sf, name):
    got = QUERIES[name](spark, sf)
    assert any(f.endswith("part.parquet") for f in got.inputFiles()) and SQL[name] == catalog.SQL["torus"]
    assert values(got) == values(catalog.torus(spark, sf))
