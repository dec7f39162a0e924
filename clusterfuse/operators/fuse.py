"""Exact fusion of clusters: the fused (n, mean, covariance) are those of all their samples together.

Three equal forms: centred (default: no cancellation), moments (sums of second moments) and gaps (pairwise distances of
centres, illustrative, quadratic in a group's size). All are native aggregates over packed slots, for any D.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import cliques, graph, pairs, stats
from .measures import measure_pairs
from ..sources.tables import discard, store


def _outer(x: Column, dim: Column) -> Column:
    """Packed x x^T."""
    return F.flatten(F.transform(F.sequence(F.lit(0), dim - 1), lambda i: F.transform(F.sequence(i, dim - 1), lambda j: F.element_at(x, (i + 1).cast("int")) * F.element_at(x, (j + 1).cast("int")))))


def _scaled(x: Column, w: Column) -> Column:
    return F.transform(x, lambda v: v * w)


def _added(x: Column, y: Column) -> Column:
    return F.zip_with(x, y, lambda a, b: a + b)


def _sum_slots(df: DataFrame, keys: list[str], column: str, name: str) -> DataFrame:
    """Slotwise sums of an array column by key: a row for each slot, added map-side, collected in order."""
    each = df.select(*keys, F.posexplode(column).alias("slot", "v")).groupBy(*keys, "slot").agg(F.sum("v").alias("v"))
    return each.groupBy(*keys).agg(F.transform(F.array_sort(F.collect_list(F.struct("slot", "v"))), lambda s: s["v"]).alias(name))


def fuse_pair(pairs_: DataFrame, form: str = "gap") -> DataFrame:
    """n, mean, cov of each pair (p, q) together; form gap (rank-one term of the centres) or moments."""
    p, q = F.col("p"), F.col("q")
    n = p["n"] + q["n"]
    mean = F.zip_with(p["mean"], q["mean"], lambda a, b: (p["n"] * a + q["n"] * b) / n)
    within = F.zip_with(p["cov"], q["cov"], lambda a, b: (p["n"] - 1) * a + (q["n"] - 1) * b)
    x = pairs_.select("model_id", "left_id", "right_id", p["dim"].alias("dim"), n.alias("n"), mean.alias("mean"), within.alias("within"), F.zip_with(p["mean"], q["mean"], lambda a, b: a - b).alias("gap"), p["n"].alias("n1"), q["n"].alias("n2"), p["mean"].alias("u"), q["mean"].alias("v"))
    if form == "gap":
        between = _scaled(_outer(F.col("gap"), F.col("dim")), F.col("n1") / F.col("n") * F.col("n2"))
    else:
        of = lambda m, w: _scaled(_outer(F.col(m), F.col("dim")), w)
        between = _added(_added(of("u", F.col("n1")), of("v", F.col("n2"))), of("mean", -F.col("n")))
    return x.select("model_id", "left_id", "right_id", "dim", "n", "mean", _scaled(_added(F.col("within"), between), 1 / (F.col("n") - 1)).alias("cov"))


def fuse_mean(clusters: DataFrame, keys: list[str]) -> DataFrame:
    """n and weighted mean by key, for any D."""
    totals = clusters.groupBy(*keys).agg(F.sum("n").alias("n"))
    sums = _sum_slots(clusters.withColumn("nm", _scaled(F.col("mean"), F.col("n"))), keys, "nm", "s")
    return totals.join(sums, keys).select(*keys, "n", _scaled(F.col("s"), 1 / F.col("n")).alias("mean"))


def fuse_by(clusters: DataFrame, keys: list[str], form: str = "centred") -> DataFrame:
    """Fusion of the clusters of each key: keys, dim, n, mean, cov, members, and the parts within and between (both over n - 1)."""
    # a table of a few numbers for each cluster: what lies below it is computed once
    c = clusters.filter("n > 0") if hasattr(clusters, "_stored_at") else store(clusters.filter("n > 0"), "to-fuse")
    base = c.groupBy(*keys).agg(F.max("dim").alias("dim"), F.array_sort(F.collect_list("cluster_id")).alias("members"))
    fused = fuse_mean(c, keys)
    within = _sum_slots(c.withColumn("w", _scaled(F.col("cov"), F.col("n") - 1)), keys, "w", "within")
    if form == "gaps":
        one = c.select(*keys, F.col("cluster_id").alias("i"), F.col("n").alias("n1"), F.col("mean").alias("u"), "dim")
        two = c.select(*keys, F.col("cluster_id").alias("j"), F.col("n").alias("n2"), F.col("mean").alias("v"))
        each = one.join(two, keys).filter("i < j").withColumn("_gap", F.zip_with("u", "v", lambda a, b: a - b))
        between = _sum_slots(each.withColumn("b", _scaled(_outer(F.col("_gap"), F.col("dim")), F.col("n1").cast("double") * F.col("n2"))), keys, "b", "b")
        between = between.join(fused.select(*keys, "n"), keys).select(*keys, _scaled(F.col("b"), 1 / F.col("n")).alias("between"))
    elif form == "moments":
        second = _sum_slots(c.withColumn("b", _scaled(_outer(F.col("mean"), F.col("dim")), F.col("n"))), keys, "b", "b")
        between = second.join(fused, keys).join(base.select(*keys, "dim"), keys).select(*keys, _added(F.col("b"), _scaled(_outer(F.col("mean"), F.col("dim")), -F.col("n"))).alias("between"))
    else:
        near = c.join(fused.select(*keys, F.col("mean").alias("centre")), keys).withColumn("_gap", F.zip_with("mean", "centre", lambda a, b: a - b))
        between = _sum_slots(near.withColumn("b", _scaled(_outer(F.col("_gap"), F.col("dim")), F.col("n"))), keys, "b", "between")
    out = base.join(fused, keys).join(within, keys).join(between, keys, "left")
    over = 1 / F.greatest(F.col("n") - 1, F.lit(1))
    b = F.coalesce("between", F.transform("within", lambda v: v * 0.0))
    return out.select(*keys, "dim", "n", "mean", _scaled(_added(F.col("within"), b), over).alias("cov"), "members", _scaled(F.col("within"), over).alias("within"), _scaled(b, over).alias("between"))


def fuse_groups(clusters: DataFrame, groups: DataFrame, form: str = "centred", hint: str | None = None) -> DataFrame:
    """One-step fusion of all groups (group_id, cluster_id); ``hint`` names the join that puts clusters to their groups."""
    members = groups.select("group_id", "cluster_id")
    return fuse_by(clusters.join(members.hint(hint) if hint else members, "cluster_id"), ["group_id"], form)


def fusion_parts(fused: DataFrame) -> DataFrame:
    """Share of the trace that lies between the centres."""
    trace = lambda c: F.aggregate(F.transform(F.sequence(F.lit(0), F.col("dim") - 1), lambda i: F.element_at(c, (i * F.col("dim") - F.floor(i * (i - 1) / 2) + 1).cast("int"))), F.lit(0.0), lambda s, v: s + v)
    x = fused.withColumn("trace_within", trace("within")).withColumn("trace_between", trace("between"))
    return x.withColumn("between_share", F.col("trace_between") / (F.col("trace_within") + F.col("trace_between")))


def fuse_models(local: DataFrame) -> DataFrame:
    """Global clusters from the local models of several owners: equal cluster_ids are fused, rows never leave their owner."""
    return fuse_by(local, ["cluster_id"])


def fusion_residual(fused: DataFrame, direct: DataFrame, keys: list[str]) -> DataFrame:
    """Relative Frobenius distance of fused and directly summarised covariances (off-diagonals count twice)."""
    both = fused.select(*keys, "dim", "n", F.col("cov").alias("x")).join(direct.select(*keys, F.col("n").alias("n_rows"), F.col("cov").alias("y")), keys)
    weights = F.flatten(F.transform(F.sequence(F.lit(0), F.col("dim") - 1), lambda i: F.transform(F.sequence(i, F.col("dim") - 1), lambda j: F.when(i == j, 1.0).otherwise(2.0))))
    norm = lambda v: F.sqrt(F.aggregate(F.zip_with(v, weights, lambda a, w: w * a * a), F.lit(0.0), lambda s, a: s + a))
    return both.select(*keys, "n", "n_rows", (norm(F.zip_with("x", "y", lambda a, b: a - b)) / norm(F.col("y"))).alias("residual"))


def candidate_pairs(clusters: DataFrame, dim: int, measure: str = "o", threshold: float = graph.THRESHOLD, criterion: str = "auto") -> DataFrame:
    """Pairs (p, q with dim, n, mean, cov) that are worth measuring.

    criterion: none (all pairs), bound (pairs of which a lower bound of o shows that they lie beyond the threshold are left
    out, so no edge is lost), oh (overlap of diagonals below the threshold: a heuristic, cheap at any D), box (2-sigma boxes
    meet, D = 2: a heuristic), or auto: bound for o, none for other measures, which the bound does not hold for."""
    columns = ["dim", "n", "mean", "cov"]
    if criterion == "auto":
        criterion = "bound" if measure == "o" else "none"
    if criterion == "none":
        return pairs.all_pairs(clusters, columns)
    plain = lambda side: F.struct(*[F.col(side)[c].alias(c) for c in columns]).alias(side)
    if criterion == "box":
        box = pairs.box_candidates(clusters)
        one = clusters.select("model_id", F.col("cluster_id").alias("left_id"), F.struct(*columns).alias("p"))
        two = clusters.select("model_id", F.col("cluster_id").alias("right_id"), F.struct(*columns).alias("q"))
        return box.join(one, ["model_id", "left_id"]).join(two, ["model_id", "right_id"]).select("model_id", "left_id", "right_id", "p", "q")
    if criterion == "oh":
        from .measures import overlap_oh

        x = store(stats.with_diagonal(clusters).select("model_id", "cluster_id", *columns, "diag", "ln_hadamard"), "with-diagonal")
        near = overlap_oh(pairs.all_pairs(x, [*columns, "diag", "ln_hadamard"])).filter(F.col("oh") < threshold)
        return near.select("model_id", "left_id", "right_id", plain("p"), plain("q"))
    if criterion != "bound":
        raise ValueError(criterion)
    x = with_volume(clusters, dim)
    near = pairs.lower_bound(pairs.all_pairs(x, [*columns, "lndet", "trace"]), dim).filter(F.col("bound").isNull() | (F.col("bound") < threshold))
    return near.select("model_id", "left_id", "right_id", plain("p"), plain("q"))


def with_volume(clusters: DataFrame, dim: int) -> DataFrame:
    """Clusters, stored, with lndet and trace: what the lower bound needs of each side, computed once and not for each pair."""
    if dim == 2:
        cov = F.col("cov")
        x = stats.with_diagonal(clusters).withColumn("lndet", stats.lndet2(F.col("n"), cov[0], cov[1], cov[2]))
    else:
        x = stats.with_stats(clusters)
    return store(x.select("model_id", "cluster_id", "dim", "n", "mean", "cov", "lndet", "trace"), "with-volume")


def fuse_overlapping(
    clusters: DataFrame, measure: str = "o", threshold: float = graph.THRESHOLD, policy: str = "largest_first", rounds: int = 1, dim: int | None = None, criterion: str = "auto", budget: int | None = None
) -> DataFrame:
    """Candidate pairs, measure, threshold, group, fuse each group in one step; up to ``rounds`` times or until nothing is fused.

    ``clusters`` is one set with distinct cluster_ids, whatever models they come from. ``criterion`` as in candidate_pairs,
    ``policy`` and ``budget`` as in disjoint_groups."""
    now, spent = clusters.withColumn("model_id", F.lit("all")), None
    for r in range(rounds):
        d = dim or now.select(F.max("dim")).first()[0]
        measured = measure_pairs(candidate_pairs(now, d, measure, threshold, criterion), d, [measure])
        found = store(graph.edges(measured, measure, threshold), "edges")
        groups = cliques.disjoint_groups(found, now, policy, budget)
        fused = fuse_groups(now, groups)
        if r == rounds - 1 or found.isEmpty():
            return fused
        now = store(fused.select(F.lit("all").alias("model_id"), F.col("group_id").alias("cluster_id"), "dim", "n", "mean", "cov"), "fused")
        discard(found, spent)
        spent = now
    return fused


def fuse_iterative(clusters: DataFrame, measure: str = "o", threshold: float = graph.THRESHOLD, rounds: str = "best") -> tuple[DataFrame, dict]:
    """Baseline: fuse the best pair (or, with rounds="mutual", all mutually best pairs) until none overlaps.

    All pairs are measured once; after that a round measures the pairs of the clusters that it has made, and pairs of
    clusters that it has not touched keep their values. Returns the clusters (with members) and counts of rounds and pair
    evaluations. Only counters reach the driver, and tables of past rounds are removed."""
    columns = ["dim", "n", "mean", "cov"]
    dim = clusters.select(F.max("dim")).first()[0]
    now = store(clusters.select(F.lit("all").alias("model_id"), "cluster_id", *columns, F.array("cluster_id").alias("members")), "step")
    held, c = now, now.count()
    counts = {"rounds": 0, "pairs": c * (c - 1) // 2}
    found = store(graph.edges(measure_pairs(pairs.all_pairs(now, columns), dim, [measure]), measure, threshold), "edges")
    while True:
        counts["rounds"] += 1
        if rounds == "mutual":
            both = graph.adjacency(found)
            first = Window.partitionBy("left_id").orderBy("weight", F.least("left_id", "right_id"), F.greatest("left_id", "right_id"))
            best = both.withColumn("r", F.row_number().over(first)).filter("r = 1").select("left_id", "right_id")
            chosen = best.join(best.select(F.col("left_id").alias("right_id"), F.col("right_id").alias("left_id")), ["left_id", "right_id"]).filter("left_id < right_id")
        else:
            chosen = found.orderBy("weight", "left_id", "right_id").limit(1).select("left_id", "right_id")
        chosen = store(chosen, "chosen")
        made = chosen.count()
        if not made:
            return now, counts
        groups = store(chosen.select(F.col("left_id").alias("group_id"), F.explode(F.array("left_id", "right_id")).alias("cluster_id")), "pairs-to-fuse")
        merged = store(now.join(groups, "cluster_id"), "merged")
        fused = fuse_by(merged, ["group_id"])
        members = merged.groupBy("group_id").agg(F.array_sort(F.flatten(F.collect_list("members"))).alias("all_members"))
        new = fused.join(members, "group_id").select(F.lit("all").alias("model_id"), F.col("group_id").alias("cluster_id"), *columns, F.col("all_members").alias("members"), F.lit(True).alias("fresh"))
        rest = now.join(groups.select("cluster_id"), "cluster_id", "left_anti").withColumn("fresh", F.lit(False))
        after = store(new.unionByName(rest), "step")
        c -= made
        counts["pairs"] += made * (c - made) + made * (made - 1) // 2
        again = graph.edges(measure_pairs(pairs.fresh_pairs(after, columns), dim, [measure]), measure, threshold)
        gone = groups.select("cluster_id")
        kept = found.join(gone.withColumnRenamed("cluster_id", "left_id"), "left_id", "left_anti").join(gone.withColumnRenamed("cluster_id", "right_id"), "right_id", "left_anti")
        later = store(kept.unionByName(again), "edges")
        discard(found, held, chosen, groups, merged)
        held, now, found = after, after.drop("fresh"), later
