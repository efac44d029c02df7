"""The nested loop join is one, and whole."""

from micro import values

from sparkgraphs.model import catalog
import sparkgraphs.ops.queries  # noqa: F401 (registers)
from sparkgraphs.queries import QUERIES


def test_nested_loop_join(spark, sf):
    got = QUERIES["op_join_nested_loop_whole"](spark, sf)
    assert "BroadcastNestedLoopJoin" in got._jdf.queryExecution().executedPlan().toString()
    keys = [r.n_nationkey for r in catalog.read(spark, sf, "nation").collect()]
    assert values(got) == sorted(((c.c_custkey, n) for c in catalog.read(spark, sf, "customer").collect() for n in keys if c.c_nationkey < n), key=repr)
