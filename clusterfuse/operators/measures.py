"""The seven pair measures: smaller means more overlap.

b Bhattacharyya, js Jensen-Shannon form (equal to b), w squared 2-Wasserstein, vr volume ratio, ab Bhattacharyya with the
arithmetic mean of volumes, o log-volume overlap, oh the same with products of diagonals in place of determinants.
Native expressions for D <= 2 (and oh for any D); batched Cholesky and eigenvalues in Arrow batches above.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions import packed as P
from ..functions.columns import let, struct_of
from ..functions.deploy import ship
from . import stats
from .pairs import lse

MEASURES = list(K.MEASURES)
#: Bytes of dense matrices that one step of a kernel handles.
STEP_BYTES = 64 << 20


def flat_pairs2(pairs: DataFrame) -> DataFrame:
    """Pairs of D = 2 clusters with scalar columns n1, u1, u2, a1, b1, c1 and n2, v1, v2, a2, b2, c2, and what the measures share.

    cov_avg is (a, b, c)_avg, the plain average; cov_fused is (a, b, c)_fused, of all samples of both with the gap of centres."""
    # bound step by step: generated code for all of it at once outgrows what the JVM compiles
    p, q, at = F.col("p"), F.col("q"), F.element_at
    side = lambda c, k, m: {f"n{k}": c["n"].cast("double"), f"{m}1": at(c["mean"], 1), f"{m}2": at(c["mean"], 2), **{f"{v}{k}": at(c["cov"], i + 1) for i, v in enumerate("abc")}}
    sides = side(p, 1, "u") | side(q, 2, "v")

    def gaps(x: Column) -> Column:
        n = x["n1"] + x["n2"]
        return let(struct_of(n=n, d1=x["u1"] - x["v1"], d2=x["u2"] - x["v2"], w1=(x["n1"] - 1) / (n - 1), w2=(x["n2"] - 1) / (n - 1), gap=x["n1"] / n * x["n2"] / (n - 1)), lambda y: covs(x, y))

    def covs(x: Column, y: Column) -> Column:
        avg = {f"{v}_avg": (x[f"{v}1"] + x[f"{v}2"]) / 2 for v in "abc"}
        within = {f"{v}_within": y["w1"] * x[f"{v}1"] + y["w2"] * x[f"{v}2"] for v in "abc"}
        fused = {f"{v}_fused": within[f"{v}_within"] + y["gap"] * y[g] * y[h] for v, g, h in (("a", "d1", "d1"), ("b", "d1", "d2"), ("c", "d2", "d2"))}
        return let(struct_of(**avg, **within, **fused), lambda z: volumes(x, y, z))

    def volumes(x: Column, y: Column, z: Column) -> Column:
        of = lambda n, c, s: stats.lndet2(n, c[f"a{s}"], c[f"b{s}"], c[f"c{s}"])
        return let(struct_of(l1=of(x["n1"], x, "1"), l2=of(x["n2"], x, "2"), l_avg=of(F.lit(3), z, "_avg"), l_fused=of(y["n"], z, "_fused"), l_within=of(y["n"], z, "_within")), lambda l: shared(x, y, z, l))

    def shared(x: Column, y: Column, z: Column, l: Column) -> Column:
        quad = lambda s: z[f"c{s}"] * y["d1"] * y["d1"] - 2 * z[f"b{s}"] * y["d1"] * y["d2"] + z[f"a{s}"] * y["d2"] * y["d2"]
        far = {"far": quad("_avg") / F.exp(l["l_avg"]), "far_within": quad("_within") / F.exp(l["l_within"]), "l_both": lse(l["l1"], l["l2"])}
        return struct_of(**{k: x[k] for k in sides}, **{k: y[k] for k in ("n", "d1", "d2", "w1", "w2", "gap")}, **{f"{v}_{s}": z[f"{v}_{s}"] for v in "abc" for s in ("avg", "within", "fused")}, **{k: l[k] for k in ("l1", "l2", "l_avg", "l_fused", "l_within")}, **far)

    return pairs.select("model_id", "left_id", "right_id", let(struct_of(**sides), gaps).alias("shared")).select("model_id", "left_id", "right_id", "shared.*")


def _counts() -> list[Column]:
    """Sample counts as they came; sums and products of them are taken in doubles, which no number of rows overflows."""
    return [F.col(c).cast("long").alias(c) for c in ("n1", "n2")]


def _kl2(s: str) -> Column:
    """Divergence of one side from the Gaussian of averages; half the gap lies on each side."""
    trace = (F.col("c_avg") * F.col(f"a{s}") - 2 * F.col("b_avg") * F.col(f"b{s}") + F.col("a_avg") * F.col(f"c{s}")) / F.exp("l_avg")
    return 0.5 * (trace + F.col("l_avg") - F.col(f"l{s}") + F.col("far") / 4 - 2)


def measure2(name: str, literal: bool = False) -> Column:
    """A measure over the columns of flat_pairs2; ``js`` is rewritten to ``b`` unless ``literal``."""
    c = F.col
    if name == "js" and literal:
        return (_kl2("1") + _kl2("2")) / 2
    if name in ("b", "js"):
        return c("far") / 8 + 0.5 * (c("l_avg") - 0.5 * (c("l1") + c("l2")))
    if name == "kl_left":
        return _kl2("1")
    if name == "kl_right":
        return _kl2("2")
    if name == "w":
        cross = c("a1") * c("a2") + 2 * c("b1") * c("b2") + c("c1") * c("c2")
        dets = F.greatest(c("a1") * c("c1") - c("b1") * c("b1"), F.lit(0.0)) * F.greatest(c("a2") * c("c2") - c("b2") * c("b2"), F.lit(0.0))
        return c("d1") * c("d1") + c("d2") * c("d2") + c("a1") + c("c1") + c("a2") + c("c2") - 2 * F.sqrt(F.greatest(cross + 2 * F.sqrt(dets), F.lit(0.0)))
    if name == "vr":
        return F.exp(c("l_fused") - c("l_both"))
    if name == "ab":
        return c("far") / 8 + 0.5 * (c("l_avg") + F.lit(K.LN2) - c("l_both"))
    if name == "o":
        return F.lit(K.LN2) + c("l_fused") - c("l_both")
    if name == "o_spread":
        return F.lit(K.LN2) + c("l_within") - c("l_both")
    if name == "o_gap":
        return F.log1p(c("gap") * c("far_within"))
    if name == "oh":
        h = lambda s: F.when((c(f"a{s}") > 0) & (c(f"c{s}") > 0), F.log(c(f"a{s}")) + F.log(c(f"c{s}")))
        return F.lit(K.LN2) + h("_fused") - lse(h("1"), h("2"))
    raise ValueError(name)


def measures1(pairs: DataFrame, which: list[str] | None = None) -> DataFrame:
    """Closed forms for D = 1."""
    p, q = F.col("p"), F.col("q")
    x = pairs.select("model_id", "left_id", "right_id", p["n"].cast("double").alias("n1"), p["mean"][0].alias("u"), p["cov"][0].alias("s1"), q["n"].cast("double").alias("n2"), q["mean"][0].alias("v"), q["cov"][0].alias("s2"))
    n, d = F.col("n1") + F.col("n2"), F.col("u") - F.col("v")
    x = x.withColumn("fused", ((F.col("n1") - 1) * F.col("s1") + (F.col("n2") - 1) * F.col("s2") + F.col("n1") / n * F.col("n2") * d * d) / (n - 1)).withColumn("avg", (F.col("s1") + F.col("s2")) / 2)
    far, total = d * d / F.col("avg") / 8, F.col("s1") + F.col("s2")
    b = far + 0.5 * F.log(F.col("avg") / F.sqrt(F.col("s1") * F.col("s2")))
    o = F.log(2 * F.col("fused") / total)
    forms = {"b": b, "js": b, "w": d * d + F.pow(F.sqrt("s1") - F.sqrt("s2"), F.lit(2)), "vr": F.col("fused") / total, "ab": far + 0.0 * d, "o": o, "oh": o}
    return x.select("model_id", "left_id", "right_id", *_counts(), *[forms[m].alias(m) for m in which or MEASURES])


def overlap_oh(pairs: DataFrame) -> DataFrame:
    """oh of pairs for any D, from n, mean and diag alone: linear in D and free of Python."""
    p, q = F.col("p"), F.col("q")
    n1, n2 = p["n"].cast("double"), q["n"].cast("double")
    n = n1 + n2
    w1, w2, gap = (n1 - 1) / (n - 1), (n2 - 1) / (n - 1), n1 / n * n2 / (n - 1)
    d2 = F.zip_with(p["mean"], q["mean"], lambda a, b: (a - b) * (a - b))
    within = F.zip_with(p["diag"], q["diag"], lambda a, b: w1 * a + w2 * b)
    fused = F.zip_with(within, d2, lambda a, g: a + gap * g)
    return pairs.withColumn("oh", F.lit(K.LN2) + stats.ln_hadamard(fused) - lse(p["ln_hadamard"], q["ln_hadamard"]))


def _arrow(pairs: DataFrame, dim: int, which: list[str], literal: bool, ridge: float | None) -> DataFrame:
    ship(pairs.sparkSession)
    p, q = F.col("p"), F.col("q")
    flat = pairs.select("model_id", "left_id", "right_id", p["n"].alias("n1"), q["n"].alias("n2"), p["mean"].alias("u"), q["mean"].alias("v"), p["cov"].alias("s"), q["cov"].alias("t"))
    step = max(1, STEP_BYTES // (8 * dim * dim * 6))

    def run(batches):
        import pyarrow as pa

        def matrix(col):
            return np.asarray(col.flatten().to_numpy(zero_copy_only=False), float).reshape(len(col), -1)

        for b in batches:
            for at in range(0, b.num_rows, step):
                x = b.slice(at, step)
                n1, n2 = (x.column(k).to_numpy(zero_copy_only=False) for k in ("n1", "n2"))
                s, t = (P.dense(matrix(x.column(k)), dim) for k in "st")
                if ridge:
                    s, t = s + ridge * np.eye(dim), t + ridge * np.eye(dim)
                out = K.pair_measures(n1, matrix(x.column("u")), s, n2, matrix(x.column("v")), t, which, literal)
                yield pa.RecordBatch.from_arrays([*[x.column(k) for k in ("model_id", "left_id", "right_id", "n1", "n2")], *[pa.array(out[m], pa.float64(), from_pandas=True) for m in which]], names=["model_id", "left_id", "right_id", "n1", "n2", *which])

    return flat.mapInArrow(run, "model_id string, left_id bigint, right_id bigint, n1 bigint, n2 bigint, " + ", ".join(f"{m} double" for m in which))


def measure_pairs(pairs: DataFrame, dim: int, measures: list[str] | None = None, engine: str = "auto", literal: bool = False, ridge: float | None = None) -> DataFrame:
    """``measures`` of pairs (model_id, left_id, right_id, p, q with n, mean, cov): JVM expressions for D <= 2, Arrow batches above or for engine="arrow"."""
    which = measures or MEASURES
    if engine == "arrow" or dim > 2 or ridge:
        return _arrow(pairs, dim, which, literal, ridge)
    if dim == 1:
        return measures1(pairs, which)
    return flat_pairs2(pairs).select("model_id", "left_id", "right_id", *_counts(), *[measure2(m, literal).alias(m) for m in which])


def literal_measures(pairs: DataFrame, dim: int) -> DataFrame:
    """b_literal and o_literal of pairs (p, q): from determinants as printed, to show what logarithms avoid; infinite or nan where they underflow."""
    ship(pairs.sparkSession)
    p, q = F.col("p"), F.col("q")
    flat = pairs.select("model_id", "left_id", "right_id", p["n"].alias("n1"), q["n"].alias("n2"), p["mean"].alias("u"), q["mean"].alias("v"), p["cov"].alias("s"), q["cov"].alias("t"))
    step = max(1, STEP_BYTES // (8 * dim * dim * 6))

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for at in range(0, b.num_rows, step):
                x = b.slice(at, step)
                rows = lambda k: np.asarray(x.column(k).flatten().to_numpy(zero_copy_only=False), float).reshape(x.num_rows, -1)  # noqa: B023, E731
                out = K.literal_forms(x.column("n1").to_numpy(), rows("u"), P.dense(rows("s"), dim), x.column("n2").to_numpy(), rows("v"), P.dense(rows("t"), dim))
                yield pa.RecordBatch.from_arrays([*[x.column(k) for k in ("model_id", "left_id", "right_id")], *[pa.array(v) for v in out.values()]], names=["model_id", "left_id", "right_id", *out])

    return flat.mapInArrow(run, "model_id string, left_id bigint, right_id bigint, b_literal double, o_literal double")


def null_corrected(measured: DataFrame, dim: int) -> DataFrame:
    """``measured`` (n1, n2, o) with o_null, the value expected of two samples of one Gaussian, and o_corrected."""
    ship(measured.sparkSession)
    sizes = measured.select("n1", "n2").distinct()

    def run(batches):
        import pyarrow as pa

        for b in batches:
            bias = [K.null_bias(dim, int(x), int(y)) for x, y in zip(b.column(0).to_pylist(), b.column(1).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(bias, pa.float64(), from_pandas=True)], names=["n1", "n2", "o_null"])

    return measured.join(sizes.mapInArrow(run, "n1 bigint, n2 bigint, o_null double"), ["n1", "n2"]).withColumn("o_corrected", F.col("o") - F.col("o_null"))
