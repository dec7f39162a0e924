"""Groups of mutually overlapping clusters: maximal cliques, and a partition of the clusters into cliques.

Cliques never cross components, so each component is one task's work; the search keeps its own stack instead of
recursing. The partition takes the largest clique first (ties: least summed weight, then smallest ids), removes it and
goes on with what is left. Finding largest cliques is NP-hard, and the search is exact however long it takes, unless the
caller sets a ``budget`` of steps: a component that exceeds it is finished greedily by degree, and its groups say
exact = false.
"""

from __future__ import annotations

import heapq
from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.deploy import ship
from ..sources.tables import discard
from . import graph


def degeneracy(near: dict[int, set[int]]) -> list[int]:
    """Vertices in the order in which the least connected one is removed: one heap of degrees, stale entries passed over."""
    degree = {v: len(n) for v, n in near.items()}
    heap, order, gone = [(d, v) for v, d in degree.items()], [], set()
    heapq.heapify(heap)
    while heap:
        d, v = heapq.heappop(heap)
        if v in gone or d != degree[v]:
            continue
        order.append(v)
        gone.add(v)
        for u in near[v]:
            if u not in gone:
                degree[u] -= 1
                heapq.heappush(heap, (degree[u], u))
    return order


def search(near: dict[int, set[int]], budget: int | None = None):
    """Maximal cliques of a graph, each once; StopIteration value True if the budget (None: no limit) sufficed. A pivot bounds the branches."""
    steps = 0
    # outer order by degeneracy keeps the first candidate sets small
    order = degeneracy(near)
    rank = {v: k for k, v in enumerate(order)}
    for v in order:
        stack = [([v], {u for u in near[v] if rank[u] > rank[v]}, {u for u in near[v] if rank[u] < rank[v]})]
        while stack:
            steps += 1
            if budget is not None and steps > budget:
                return False
            chosen, open_, done = stack.pop()
            if not open_ and not done:
                yield sorted(chosen)
                continue
            if not open_:
                continue
            pivot = max(open_ | done, key=lambda u: len(near[u] & open_))
            for u in sorted(open_ - near[pivot]):
                stack.append(([*chosen, u], open_ & near[u], done & near[u]))
                open_, done = open_ - {u}, done | {u}
    return True


def _all_cliques(near, budget):
    found, it = [], search(near, budget)
    while True:
        try:
            found.append(next(it))
        except StopIteration as end:
            return found, bool(end.value)


def partition(nodes: list[int], weight: dict[tuple[int, int], float], budget: int | None = None) -> list[tuple[list[int], bool]]:
    """Disjoint cliques that cover ``nodes``, with whether each was found exactly. weight: of edges (a < b)."""
    near: dict[int, set[int]] = {v: set() for v in nodes}
    for a, b in weight:
        near[a].add(b)
        near[b].add(a)
    found, exact = _all_cliques({v: n for v, n in near.items() if n}, budget)
    out, left = [], set(nodes)
    if exact:
        total = lambda c: round(sum(weight[(a, b)] for i, a in enumerate(c) for b in c[i + 1 :]), 12)
        # parts of the maximal cliques are the cliques of what is left; a clique is ranked anew when it has lost a member
        rest, holders = [tuple(c) for c in found], defaultdict(list)
        for k, c in enumerate(rest):
            for v in c:
                holders[v].append(k)
        heap = [(-len(c), total(c), c, k) for k, c in enumerate(rest)]
        heapq.heapify(heap)
        while heap:
            _, _, c, k = heapq.heappop(heap)
            if c != rest[k] or len(c) < 2:
                continue
            out.append((list(c), True))
            left -= set(c)
            for j in {j for v in c for j in holders[v]}:
                rest[j] = tuple(v for v in rest[j] if v in left)
                if len(rest[j]) > 1:
                    heapq.heappush(heap, (-len(rest[j]), total(rest[j]), rest[j], j))
        return out + [([v], True) for v in sorted(left)]
    while left:
        group: list[int] = []
        open_ = set(left)
        while open_:
            v = min(open_, key=lambda x: (-len(near[x] & open_), x))
            group.append(v)
            open_ &= near[v]
        out.append((sorted(group), False))
        left -= set(group)
    return out


def _by_component(found: DataFrame) -> DataFrame:
    comp = graph.components(found)
    return found.join(comp.select(F.col("cluster_id").alias("left_id"), "component_id"), "left_id")


def maximal_cliques(found: DataFrame, budget: int | None = None) -> DataFrame:
    """members and size of every maximal clique of the edges (left_id, right_id); an error if a component exceeds a ``budget`` that was set."""
    ship(found.sparkSession)

    def run(t):
        import pyarrow as pa

        near: dict[int, set[int]] = {}
        for a, b in zip(t["left_id"].to_pylist(), t["right_id"].to_pylist()):
            near.setdefault(a, set()).add(b)
            near.setdefault(b, set()).add(a)
        cliques, exact = _all_cliques(near, budget)
        if not exact:
            raise RuntimeError("component exceeds the clique budget; use disjoint_groups, which falls back to a greedy cover")
        return pa.table({"members": pa.array(sorted(cliques), pa.list_(pa.int64())), "size": pa.array([len(c) for c in sorted(cliques)], pa.int32())})

    return _by_component(found).groupBy("component_id").applyInArrow(run, "members array<bigint>, size int")


def disjoint_groups(found: DataFrame, nodes: DataFrame, policy: str = "largest_first", budget: int | None = None) -> DataFrame:
    """group_id (smallest member), cluster_id, size, exact: every node in one group.

    policy: largest_first, greedy (by degree, for giant components) or components (transitive closure, which over-merges)."""
    if policy == "components":
        comp = graph.components(found, nodes)
        sizes = comp.groupBy("component_id").agg(F.count(F.lit(1)).cast("int").alias("size"))
        return comp.join(sizes, "component_id").select(F.col("component_id").alias("group_id"), "cluster_id", "size", F.lit(True).alias("exact"))
    ship(found.sparkSession)
    steps = 0 if policy == "greedy" else budget

    def run(t):
        import pyarrow as pa

        weight = {(min(a, b), max(a, b)): w for a, b, w in zip(t["left_id"].to_pylist(), t["right_id"].to_pylist(), t["weight"].to_pylist())}
        groups = partition(sorted({v for e in weight for v in e}), weight, steps)
        rows = [(min(g), v, len(g), ok) for g, ok in groups for v in g]
        return pa.table({"group_id": pa.array([r[0] for r in rows], pa.int64()), "cluster_id": pa.array([r[1] for r in rows], pa.int64()), "size": pa.array([r[2] for r in rows], pa.int32()), "exact": pa.array([r[3] for r in rows], pa.bool_())})

    grouped = _by_component(found).groupBy("component_id").applyInArrow(run, "group_id bigint, cluster_id bigint, size int, exact boolean")
    return with_singletons(grouped, nodes)


def with_singletons(groups: DataFrame, nodes: DataFrame) -> DataFrame:
    """Groups of all nodes: those in none are groups of one."""
    out = nodes.select("cluster_id").join(groups, "cluster_id", "left")
    return out.select(F.coalesce("group_id", "cluster_id").alias("group_id"), "cluster_id", F.coalesce("size", F.lit(1)).alias("size"), F.coalesce("exact", F.lit(True)).alias("exact"))


def cliques_by_join(found: DataFrame) -> DataFrame:
    """Maximal cliques by joins alone: cliques of k grow to k + 1 by a common later neighbour, until none grows.

    Every clique of every size is a row of its level, so this suits sparse graphs; a maximal clique of m members costs
    2**m rows, and maximal_cliques has no such cost."""
    pairs = graph.store(found.select(F.least("left_id", "right_id").alias("x"), F.greatest("left_id", "right_id").alias("y")).distinct(), "oriented")
    both = pairs.union(pairs.select(F.col("y"), F.col("x")))
    near = graph.store(both.groupBy("x").agg(F.collect_set("y").alias("near")), "near")
    of = lambda name, to: near.select(F.col("x").alias(name), F.col("near").alias(to))
    level = graph.store(pairs.join(near, "x").join(of("y", "near_y"), "y").select(F.array("x", "y").alias("members"), F.array_intersect("near", "near_y").alias("common")), "cliques")
    out = None
    while not level.isEmpty():
        whole = graph.store(level.filter(F.size("common") == 0).select("members"), "maximal")
        out = whole if out is None else out.union(whole)
        grown = level.select("members", "common", F.explode(F.filter("common", lambda v: v > F.element_at("members", -1))).alias("v"))
        later = graph.store(grown.join(of("v", "of_v"), "v").select(F.concat("members", F.array("v")).alias("members"), F.array_intersect("common", "of_v").alias("common")), "cliques")
        discard(level)
        level = later
    out = level.select("members") if out is None else out
    return out.select("members", F.size("members").alias("size"))


def cliques_recursive(found: DataFrame) -> DataFrame:
    """The same growth as one recursive SQL query, for small graphs: Spark bounds the levels and rows of a recursion."""
    spark = found.sparkSession
    pairs = found.select(F.least("left_id", "right_id").alias("x"), F.greatest("left_id", "right_id").alias("y")).distinct()
    near = pairs.union(pairs.select("y", "x")).groupBy("x").agg(F.collect_set("y").alias("near"))
    return spark.sql(
        """
        WITH RECURSIVE n AS (SELECT x, near FROM {near}),
        grown(members, common) AS (
          SELECT array(p.x, p.y), array_intersect(a.near, b.near) FROM {pairs} p JOIN n a ON a.x = p.x JOIN n b ON b.x = p.y
          UNION ALL
          SELECT concat(g.members, array(p.y)), array_intersect(g.common, b.near)
          FROM grown g JOIN {pairs} p ON p.x = element_at(g.members, -1) AND array_contains(g.common, p.y) JOIN n b ON b.x = p.y)
        SELECT members, size(members) AS size FROM grown WHERE size(common) = 0
        """,
        near=near,
        pairs=pairs,
    )
