"""Work of the pipeline's near copies that grows with the members of crowded postings and is done once."""

import numpy as np
from delimscan.llm import simhash


def _rows_made(spark, first, *keys):
    """Rows that joins on ``keys`` gave in the SQL executions from ``first`` on."""
    store, made = spark._jsparkSession.sharedState().statusStore(), 0
    for e in range(first, store.executionsCount()):
        values = store.executionMetrics(e)
        nodes = store.planGraph(e).allNodes()
        for node in (nodes.apply(i) for i in range(nodes.size())):
            if "Join" in node.name() and all(f"{k}#" in node.desc() for k in keys):
                for m in (node.metrics().apply(i) for i in range(node.metrics().size())):
                    if m.name() == "number of output rows" and values.contains(m.accumulatorId()):
                        made += int(values.apply(m.accumulatorId()).replace(",", ""))
    return made


def _listed(spark, members):
    """Three crowded postings of all ``members``, each in a group of its own, a bit from the next."""
    w = [1 << (i % 60) for i in range(members)]
    sketch = bytearray(simhash.SKETCH // 8)
    table = spark.createDataFrame([(i, 100 + i, w[i], i // 60, 50, sketch) for i in range(members)], "no long, root long, w long, w2 long, n long, sketch binary")
    posts = spark.createDataFrame([(c, 7, w[i], i // 60) for c in range(3) for i in range(members)], "combo int, key long, w long, w2 long")
    return simhash.durable(posts), simhash.durable(table)


def test_listed_members_are_joined_once_and_grow_with_the_group(spark):
    for members in (40, 80):
        posts, table = _listed(spark, members)
        first = spark._jsparkSession.sharedState().statusStore().executionsCount()
        pairs, waiting = simhash._apart(posts, table, 0.8, 10**6)
        got = {(min(r.u, r.v), max(r.u, r.v)) for r in pairs.collect()}
        fp = [(np.uint64(1 << (i % 60)), np.uint64(i // 60)) for i in range(members)]
        far = lambda i, j: (np.array([fp[i][0] ^ fp[j][0]]), np.array([fp[i][1] ^ fp[j][1]]))
        want = {(i, j) for j in range(members) for i in range(j) if any(simhash.first_meeting(np.array([c]), *far(i, j))[0] for c in range(3))}
        assert got == want and got and not waiting
        assert _rows_made(spark, first, "w", "w2") == 3 * members
