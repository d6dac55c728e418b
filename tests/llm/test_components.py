"""The finding on the pipeline (round 2): joins by node in near_dedup read every link again in each round."""

import numpy as np
import pytest

from predradius.llm import near_dedup


def joined_rows(spark, from_execution):
    """Rows that the joins of all executions from this one on made."""
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    store, total = spark._jsparkSession.sharedState().statusStore(), 0
    listed = store.executionsList()
    ids = [listed.apply(i).executionId() for i in range(listed.size())]
    for one in (i for i in ids if i >= from_execution):
        values, nodes = store.executionMetrics(one), store.planGraph(one).allNodes()
        for node in (nodes.apply(i) for i in range(nodes.size())):
            if "Join" in node.name():
                for metric in (node.metrics().apply(i) for i in range(node.metrics().size())):
                    if metric.name() == "number of output rows" and values.contains(metric.accumulatorId()):
                        total += int(values.apply(metric.accumulatorId()).replace(",", ""))
    return total, max(ids, default=-1) + 1


def reachable(links):
    label = {x: x for link in links for x in link}
    changed = True
    while changed:
        changed = False
        for a, b in links:
            least = min(label[a], label[b])
            changed |= label[a] != least or label[b] != least
            label[a] = label[b] = least
    return label


def test_components_read_links_about_once(spark):
    links = np.unique(np.random.default_rng(3).integers(0, 200, (2000, 2)), axis=0).tolist()
    start = joined_rows(spark, 1 << 60)[1]
    got = {r["node"]: r["component"] for r in near_dedup.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == reachable(links)
    assert joined_rows(spark, start)[0] < 3 * len(links)


@pytest.mark.parametrize("shape", ["path", "sparse", "loops"])
def test_components_of_odd_graphs(spark, shape):
    draw = np.random.default_rng(4)
    links = {"path": [(i + 1, i) for i in range(60)], "sparse": [tuple(r) for r in draw.integers(0, 300, (280, 2)).tolist()], "loops": [(5, 5), (8, 7), (7, 8), (9, 8)]}[shape]
    got = {r["node"]: r["component"] for r in near_dedup.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == reachable(links)
