import hashlib

from pyspark.sql import functions as F

from tablevec.operators import graph
from tablevec.plans.stages import Stages


def _star(spark, n=40):
    """Values 0 to n - 1, all linked with value n and the column 'a', which are hubs; value n + 1 has its column alone."""
    nodes = spark.createDataFrame([(i, "a") for i in range(n)] + [(n, "b"), (n + 1, "b")], "node_id long, category string")
    pairs = [("r", k, *(e if not k else e[::-1])) for e in [(i, n) for i in range(n)] for k in (False, True)]
    return nodes, spark.createDataFrame(pairs + [("s", *p[1:]) for p in pairs], "rel string, rel_inv boolean, src long, dst long")


def _plain(nodes, links, per_node, length):
    """The walks by dictionaries: sorted distinct neighbours, of which an md5 picks one."""
    around = {}
    for a, b in {(str(r["src"]), str(r["dst"])) for r in links.collect()} | {(str(r["node_id"]), r["category"]) for r in nodes.collect()}:
        around.setdefault(a, set()).add(b)
        around.setdefault(b, set()).add(a)
    around, out = {k: sorted(v) for k, v in around.items()}, {}
    for head in around:
        for k in range(per_node):
            path = [head]
            for step in range(1, length):
                near = around[path[-1]]
                path.append(near[int(hashlib.md5(f"1/{head}#{k}/{step}".encode()).hexdigest()[:8], 16) % len(near)])
            out[f"{head}#{k}"] = path
    return out


def test_walks_join_rows_of_many_neighbours(spark, monkeypatch):
    nodes, links = _star(spark)
    wanted = _plain(nodes, links, 3, 11)
    for size in (7, 1024):
        monkeypatch.setattr(graph, "PLACES", size, raising=False)
        for build in (graph.build_graph, graph.build_unlabelled):
            got = {r["walk_id"]: r["path"] for r in graph.walks(build(nodes, links), 3, 11).collect()}
            assert got == wanted
    monkeypatch.setattr(graph, "PLACES", 7)
    many, around = graph.places(graph.build_unlabelled(nodes, links)[1], Stages(spark, "test"))
    assert {r["_many"]: r["_degree"] for r in many.collect()} == {"40": 41, "a": 40}
    assert around.agg(F.max(F.size("next"))).first()[0] == 7
    assert around.count() == 40 + 1 + 1 + 6 + 6
