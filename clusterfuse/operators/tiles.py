"""All pairs of D = 2 clusters, tile by tile: a tile is two blocks of clusters, whose pairs exist in a worker's cache only.

What is asked of the pairs (rows, extremes, nearest ones) leaves the tile; no join makes a row for each pair. Values are those
of measures.measure2, and null where it has none."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.deploy import ship

#: Clusters of a block at most and at least (about), pairs of one step of a kernel, and tiles that a task handles beyond 32 tasks a core.
BLOCK, SMALL_BLOCK, STEP, TASK_TILES = 2048, 256, 32_768, 64
SIDE = "id", "n", "m1", "m2", "a", "b", "c"


def tiles(clusters: DataFrame) -> DataFrame:
    """model_id, i, j (i <= j) and the blocks p and q: arrays of (id, n, m1, m2, a, b, c), sorted by id. Each cluster is copied once for each block."""
    most = clusters.groupBy("model_id").count().agg(F.coalesce(F.max("count"), F.lit(0))).first()[0]
    cores = clusters.sparkSession.sparkContext.defaultParallelism
    each = min(BLOCK, max(SMALL_BLOCK, most // 8))
    k = max(1, -(-most // each))
    n_tiles = k * (k + 1) // 2
    tasks = min(n_tiles, max(32 * cores, n_tiles // TASK_TILES))
    at = F.element_at
    x = clusters.select("model_id", F.pmod(F.xxhash64("cluster_id"), F.lit(k)).cast("int").alias("i"), F.struct(F.col("cluster_id").alias("id"), F.col("n").cast("double").alias("n"), at("mean", 1).alias("m1"), at("mean", 2).alias("m2"), *[at("cov", s + 1).alias(v) for s, v in enumerate("abc")]).alias("x"))
    held = x.groupBy("model_id", "i").agg(F.array_sort(F.collect_list("x")).alias("p"))
    left = held.withColumn("j", F.explode(F.sequence(F.col("i"), F.lit(k - 1))))
    right = held.select("model_id", F.col("i").alias("j"), F.col("p").alias("q")).withColumn("i", F.explode(F.sequence(F.lit(0), F.col("j"))))
    # as many tasks as were asked for: sizes in bytes say nothing of the work
    on = ["model_id", "i", "j"]
    return left.repartition(tasks, *on).join(right.repartition(tasks, *on).hint("merge"), on)


class Block:
    """A block's columns, with e and l, the determinants and their logs (0 and nan without a volume), r, the raw ones, and h, the log of the diagonal's product."""

    def __init__(self, columns: dict[str, np.ndarray]):
        self.columns = columns
        self.__dict__.update(columns)

    @classmethod
    def of(cls, rows) -> Block:
        parts = dict(zip(SIDE, (x.to_numpy(zero_copy_only=False) for x in rows.flatten())))
        n, a, b, c = (parts[k] for k in "nabc")
        with np.errstate(all="ignore"):
            det = a * c - b * b
            e = np.where((n > 2) & (a > 0) & (det > 1e-12 * a * c), det, 0.0)
            parts |= {"e": e, "l": np.where(e > 0, np.log(e), np.nan), "r": np.maximum(det, 0.0), "h": np.where((a > 0) & (c > 0), np.log(a) + np.log(c), np.nan)}
        return cls(parts)

    def part(self, at: slice, axis: int) -> Block:
        return Block({k: v[at][:, None] if axis == 0 else v[at][None, :] for k, v in self.columns.items()})


def pair_values(p: Block, q: Block, which) -> dict[str, np.ndarray]:
    """The asked measures of all pairs of p (a column) and q (a row); js_literal is js by its divergences."""
    out, which = {}, set(which)
    d1, d2 = p.m1 - q.m1, p.m2 - q.m2
    d11, d22, d12 = d1 * d1, d2 * d2, d1 * d2
    if which & {"ab", "vr", "o"}:
        e = p.e + q.e
        l_both = np.log(np.where(e > 0, e, np.nan))
    if which & {"b", "js", "js_literal", "ab"}:
        aa, ba, ca = (p.a + q.a) / 2, (p.b + q.b) / 2, (p.c + q.c) / 2
        full = aa * ca
        det = full - ba * ba
        det = np.where((aa > 0) & (det > 1e-12 * full), det, np.nan)
        l_avg, far = np.log(det), (ca * d11 - 2 * (ba * d12) + aa * d22) / det
        if which & {"b", "js"}:
            out["b"] = out["js"] = far / 8 + 0.5 * (l_avg - 0.5 * (p.l + q.l))
        if "js_literal" in which:
            kl = [0.5 * ((ca * s.a - 2 * (ba * s.b) + aa * s.c) / det + l_avg - s.l + far / 4 - 2) for s in (p, q)]
            out["js_literal"] = (kl[0] + kl[1]) / 2
        if "ab" in which:
            out["ab"] = far / 8 + 0.5 * (l_avg + K.LN2 - l_both)
    if which & {"vr", "o", "oh"}:
        n = p.n + q.n
        w = 1 / (n - 1)
        w1, w2, gap = (p.n - 1) * w, (q.n - 1) * w, p.n / n * q.n * w
        af, cf = w1 * p.a + w2 * q.a + gap * d11, w1 * p.c + w2 * q.c + gap * d22
        if which & {"vr", "o"}:
            bf, full = w1 * p.b + w2 * q.b + gap * d12, af * cf
            det = full - bf * bf
            l_fused = np.log(np.where((n > 2) & (af > 0) & (det > 1e-12 * full), det, np.nan))
            if "vr" in which:
                out["vr"] = np.exp(l_fused - l_both)
            if "o" in which:
                out["o"] = K.LN2 + l_fused - l_both
        if "oh" in which:
            fine = (af > 0) & (cf > 0)
            out["oh"] = K.LN2 + np.where(fine, np.log(np.where(fine, af, 1.0)) + np.log(np.where(fine, cf, 1.0)), np.nan) - K.lse(p.h, q.h)
    if "w" in which:
        cross = p.a * q.a + 2 * (p.b * q.b) + p.c * q.c + 2 * np.sqrt(p.r * q.r)
        out["w"] = d11 + d22 + (p.a + p.c) + (q.a + q.c) - 2 * np.sqrt(np.maximum(cross, 0.0))
    return {m: out[m] for m in which}


def _steps(p: Block, q: Block, same: bool):
    """(part of p, part of q, which of their pairs count or None for all) over a tile; a block's pairs with itself count once."""
    rows, n = max(1, STEP // max(1, len(q.id))), len(p.id)
    for lo in range(0, n, rows):
        at = slice(lo, min(n, lo + rows))
        one, two = p.part(at, 0), q.part(slice(lo if same else 0, None), 1)
        yield one, two, np.arange(two.id.shape[1])[None, :] > np.arange(one.id.shape[0])[:, None] if same else None


def _over_tiles(clusters: DataFrame, work, schema: str) -> DataFrame:
    """``work(model_id, p, q, same)``, which yields record batches, over all tiles."""
    ship(clusters.sparkSession)

    def run(batches):
        with np.errstate(all="ignore"):
            for b in batches:
                for k in range(b.num_rows):
                    model, same = b.column(0)[k].as_py(), b.column(1)[k].as_py()
                    p = Block.of(b.column(2)[k].values)
                    yield from work(model, p, p if same else Block.of(b.column(3)[k].values), same)

    return tiles(clusters).select("model_id", F.expr("i = j").alias("same"), "p", "q").mapInArrow(run, schema)


def measured(clusters: DataFrame, which=K.MEASURES) -> DataFrame:
    """model_id, left_id, right_id and the measures of every pair of D = 2 clusters; js is b."""
    sent = [m for m in dict.fromkeys("b" if m == "js" else m for m in which)]

    def work(model, p, q, same):
        import pyarrow as pa

        for one, two, counts in _steps(p, q, same):
            values = pair_values(one, two, sent)
            chosen = (lambda x: x.ravel()) if counts is None else (lambda x: x[counts])  # noqa: B023
            left = chosen(np.minimum(one.id, two.id))
            cols = [pa.array([model], pa.string()).take(pa.array(np.zeros(len(left), np.int8))), pa.array(left), pa.array(chosen(np.maximum(one.id, two.id)))]
            yield pa.RecordBatch.from_arrays([*cols, *[pa.array(chosen(values[m]), pa.float64(), from_pandas=True) for m in sent]], names=["model_id", "left_id", "right_id", *sent])

    out = _over_tiles(clusters, work, "model_id string, left_id bigint, right_id bigint, " + ", ".join(f"{m} double" for m in sent))
    return out.select("model_id", "left_id", "right_id", *[F.col("b" if m == "js" else m).alias(m) for m in which])


def largest_gap(clusters: DataFrame, which, gap) -> DataFrame:
    """n_pairs and gap: the largest value of ``gap`` (of the measures of ``which``, as arrays) over all pairs that have one."""

    def work(model, p, q, same):
        import pyarrow as pa

        n, most = 0, np.nan
        for one, two, counts in _steps(p, q, same):
            x = gap(pair_values(one, two, which))
            n += x.size if counts is None else int(counts.sum())
            most = np.fmax(most, np.fmax.reduce(x.ravel() if counts is None else x[counts], initial=np.nan))
        yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([float(most)], pa.float64(), from_pandas=True)], names=["n_pairs", "gap"])

    return _over_tiles(clusters, work, "n_pairs bigint, gap double").agg(F.coalesce(F.sum("n_pairs"), F.lit(0)).alias("n_pairs"), F.max("gap").alias("gap"))


_FOUND = "model_id string, left_id bigint, right_id bigint, value double"


def _found(model, left, right, value):
    """Rows of _FOUND; infinite values were put in for missing ones."""
    import pyarrow as pa

    return pa.RecordBatch.from_arrays([pa.array([model] * len(left), pa.string()), pa.array(left), pa.array(right), pa.array(value, mask=np.isinf(value))], names=["model_id", "left_id", "right_id", "value"])


def least(clusters: DataFrame, measure: str, k: int) -> DataFrame:
    """left_id, right_id, value of the ``k`` pairs with the least values, in order; ties by the ids, missing values last. Exact: each tile sends its k least."""

    def work(model, p, q, same):
        left, right, value = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        for one, two, counts in _steps(p, q, same):
            x = pair_values(one, two, [measure])[measure]
            x = np.where(np.isnan(x), np.inf, x)
            # no pair beyond the k least so far, and none of the step beyond its own k least
            near = x <= (value[k - 1] if len(value) >= k else np.partition(x, k - 1, None)[k - 1] if counts is None and x.size > k else np.inf)
            u, v = np.nonzero(near if counts is None else near & counts)
            ids = one.id[u, 0], two.id[0, v]
            left, right, value = np.append(left, np.minimum(*ids)), np.append(right, np.maximum(*ids)), np.append(value, x[u, v])
            best = np.lexsort((right, left, value))[:k]
            left, right, value = left[best], right[best], value[best]
        yield _found(model, left, right, value)

    return _over_tiles(clusters, work, _FOUND).orderBy(F.asc_nulls_last("value"), "left_id", "right_id").limit(k).select("left_id", "right_id", "value")


def nearest(clusters: DataFrame, measure: str, k: int) -> DataFrame:
    """model_id, left_id, right_id, value, place: the ``k`` clusters with the least values for each cluster; ties by the smaller id, missing values last. Exact: each tile sends the k nearest of its clusters."""

    def nearest_of(x: np.ndarray, rows: np.ndarray, others: np.ndarray):
        # ids are sorted, so the first of equal values has the smallest
        every = np.arange(len(x))
        for _ in range(min(k, x.shape[1])):
            at = x.argmin(1)
            value = x[every, at]
            fine = value < np.inf
            yield rows[fine], others[at[fine]], np.where(value[fine] == _MISSING, np.inf, value[fine])
            x[every, at] = np.inf

    def work(model, p, q, same):
        x = np.empty((len(p.id), len(q.id)))
        rows = max(1, STEP // max(1, len(q.id)))
        for lo in range(0, len(x), rows):
            x[lo : lo + rows] = pair_values(p.part(slice(lo, lo + rows), 0), q.part(slice(None), 1), [measure])[measure]
        x[np.isnan(x)] = _MISSING
        if same:
            np.fill_diagonal(x, np.inf)
        across = None if same else x.T.copy()
        for found in nearest_of(x, p.id, q.id):
            yield _found(model, *found)
        for found in () if same else nearest_of(across, q.id, p.id):
            yield _found(model, *found)

    w = Window.partitionBy("model_id", "left_id").orderBy(F.asc_nulls_last("value"), "right_id")
    return _over_tiles(clusters, work, _FOUND).withColumn("place", F.row_number().over(w)).filter(F.col("place") <= k)


_MISSING = np.finfo(float).max
