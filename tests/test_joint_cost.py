"""The joint cost finishes with net1's links before net2's closeness is formed, and deals each of its tables out once."""

from pyspark.sql import functions as F

import __spark_entry__ as entry
from mutualgraph.operators import partitions
from mutualgraph.sources import networks


def test_links_are_done_before_closeness(spark, tiny):
    plan = entry.queries()["joint_cost"](spark, tiny)._jdf.queryExecution().executedPlan().toString()
    assert "l_partkey" not in plan and "o_custkey" not in plan, plan


def test_links_are_dealt_out_once(spark, tiny):
    plan = networks.orders_net(spark, tiny).follow._jdf.queryExecution().executedPlan().toString()
    keys = [part.split(")", 1)[0] for part in plan.split("hashpartitioning(")[1:]]
    assert any("src#" in k for k in keys) and not any("dst#" in k or "post_id#" in k and "l_partkey#" in k for k in keys), plan


def test_flow_both_ways(spark):
    links = spark.createDataFrame([(1, 2), (2, 1), (2, 3), (3, 4), (4, 4), (5, 1)], "src long, dst long").withColumn("s", F.lit(1.0))
    part = spark.createDataFrame([(1, 0), (2, 0), (3, 1), (4, 2), (5, 2)], "user_id long, cluster int")
    both = links.union(links.select("dst", "src", "s"))
    flow = lambda df: sorted(tuple(r) for r in df.select("c1", "c2", "w").collect())
    assert flow(partitions.both_ways(partitions.cluster_flow(links, part))) == flow(partitions.cluster_flow(both, part))
