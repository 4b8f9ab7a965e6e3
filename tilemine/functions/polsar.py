"""Polarimetric decomposition as column expressions: everything stays in generated code.

A coherence matrix of three components is nine double columns: t11 t22 t33 and the real and imaginary
parts (r, i) of t12 t13 t23.  Its eigenvalues come from the trigonometric roots of the characteristic cubic
and the first components of its eigenvectors from the eigenvalues of the lower-right minor, so no
Python runs; ``angles`` (numpy) is for rows whose eigenvalues coincide and for all eigenvector angles.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from tilemine.functions.complexes import Cx

T_COLUMNS = ["t11", "t22", "t33", "t12r", "t12i", "t13r", "t13i", "t23r", "t23i"]
EPS = 1e-12
#: Relative to the trace.  The trigonometric roots lose half the digits where two of them meet.
GAP = 1e-6


def scatter(field_h: Cx, field_v: Cx) -> tuple[Cx, Cx]:
    """Backscattered field of an incident one."""
    hh, hv, vh, vv = map(Cx.of, ("hh", "hv", "vh", "vv"))
    return hh * field_h + hv * field_v, vh * field_h + vv * field_v


def powers(px: DataFrame) -> DataFrame:
    """Co- and cross-polarised power of each pixel."""
    hh, hv, vh, vv = map(Cx.of, ("hh", "hv", "vh", "vv"))
    return px.withColumns({"p_co": hh.power() + vv.power(), "p_cross": hv.power() + vh.power()})


def reciprocal(px: DataFrame, mode: str = "average") -> DataFrame:
    """Equal cross channels: their average, or the hv channel for both."""
    hv, vh = Cx.of("hv"), Cx.of("vh")
    cross = (hv + vh).scale(0.5) if mode == "average" else hv
    return px.withColumns({"hv_re": cross.re, "hv_im": cross.im, "vh_re": cross.re, "vh_im": cross.im})


def pauli(n_dim: int = 3) -> list[Cx]:
    """The Pauli target vector of a pixel, three components or, for bistatic data, four."""
    hh, hv, vh, vv = map(Cx.of, ("hh", "hv", "vh", "vv"))
    k = 1 / math.sqrt(2)
    first = [(hh + vv).scale(k), (hh - vv).scale(k)]
    if n_dim == 3:
        return [*first, hv.scale(2 * k)]
    return [*first, (hv + vh).scale(k), (hv - vh).times_j().scale(k)]


def _outer(vector: list[Cx]) -> dict[str, Column]:
    out: dict[str, Column] = {}
    for i, a in enumerate(vector, 1):
        out[f"t{i}{i}"] = a.power()
        for j, b in enumerate(vector[i:], i + 1):
            c = a * b.conj()
            out[f"t{i}{j}r"], out[f"t{i}{j}i"] = c.re, c.im
    return out


def coherence(px: DataFrame, n_dim: int = 3, keep: tuple[str, ...] = ("product_id", "row", "col")) -> DataFrame:
    """Single-look coherence of each pixel: the target vector times its conjugate transpose."""
    return px.select(*keep, *[c.alias(n) for n, c in _outer(pauli(n_dim)).items()])


def cross_products(px: DataFrame, keep: tuple[str, ...] = ("product_id", "row", "col")) -> DataFrame:
    """The six products of reciprocal channels: three powers, three correlations."""
    hh, hv, vv = map(Cx.of, ("hh", "hv", "vv"))
    c, a, b = hh * vv.conj(), hh * hv.conj(), hv * vv.conj()
    return px.select(*keep, hh.power().alias("p_hh"), hv.power().alias("p_hv"), vv.power().alias("p_vv"), *c.named("hhvv"), *a.named("hhhv"), *b.named("hvvv"))


def coherence_from_products(cp: DataFrame, keep: tuple[str, ...] = ("product_id", "row", "col")) -> DataFrame:
    c, a, b = Cx.of("hhvv"), Cx.of("hhhv"), Cx.of("hvvv")
    t13, t23 = a + b.conj(), a - b.conj()
    both = (F.col("p_hh") + F.col("p_vv")) / 2
    return cp.select(
        *keep, (both + c.re).alias("t11"), (both - c.re).alias("t22"), (2 * F.col("p_hv")).alias("t33"), ((F.col("p_hh") - F.col("p_vv")) / 2).alias("t12r"), (-c.im).alias("t12i"),
        t13.re.alias("t13r"), t13.im.alias("t13i"), t23.re.alias("t23r"), t23.im.alias("t23i"),
    )


def eigenvalues(df: DataFrame) -> DataFrame:
    """Adds l1 >= l2 >= l3 >= 0."""
    off = sum((F.col(f"t{ij}{p}") * F.col(f"t{ij}{p}") for ij in ("12", "13", "23") for p in "ri"), F.lit(0.0))
    df = df.withColumn("_m", (F.col("t11") + F.col("t22") + F.col("t33")) / 3).withColumn("_off", off)
    df = df.withColumns({f"_k{i}": F.col(f"t{i}{i}") - F.col("_m") for i in (1, 2, 3)})
    df = df.withColumn("_p", F.sqrt((F.col("_k1") * F.col("_k1") + F.col("_k2") * F.col("_k2") + F.col("_k3") * F.col("_k3") + 2 * F.col("_off")) / 6))
    t12, t13, t23 = (Cx(F.col(f"t{ij}r"), F.col(f"t{ij}i")) for ij in ("12", "13", "23"))
    det = F.col("_k1") * F.col("_k2") * F.col("_k3") + 2 * (t12 * t23 * t13.conj()).re - F.col("_k1") * t23.power() - F.col("_k2") * t13.power() - F.col("_k3") * t12.power()
    ratio = F.when(F.col("_p") > EPS * F.col("_m"), F.least(F.lit(1.0), F.greatest(F.lit(-1.0), F.try_divide(det, 2 * F.col("_p") * F.col("_p") * F.col("_p"))))).otherwise(F.lit(1.0))
    df = barrier(df.withColumn("_phi", F.acos(ratio) / 3))
    df = df.withColumn("l1", F.col("_m") + 2 * F.col("_p") * F.cos("_phi")).withColumn("_l3", F.col("_m") + 2 * F.col("_p") * F.cos(F.col("_phi") + 2 * math.pi / 3))
    df = df.withColumn("l2", F.greatest(F.lit(0.0), 3 * F.col("_m") - F.col("l1") - F.col("_l3"))).withColumn("l3", F.greatest(F.lit(0.0), F.col("_l3")))
    return barrier(df.drop("_m", "_off", "_k1", "_k2", "_k3", "_p", "_phi", "_l3"))


def alphas(df: DataFrame) -> DataFrame:
    """Adds alpha1..alpha3 of the eigenvectors (needs l1..l3) and ``degenerate``, where two eigenvalues coincide."""
    half, diff = (F.col("t22") + F.col("t33")) / 2, (F.col("t22") - F.col("t33")) / 2
    root = F.sqrt(diff * diff + F.col("t23r") * F.col("t23r") + F.col("t23i") * F.col("t23i"))
    df = df.withColumns({"_u1": half + root, "_u2": half - root})
    trace = F.col("l1") + F.col("l2") + F.col("l3")
    df = df.withColumn("degenerate", (F.col("l1") - F.col("l2") < GAP * trace) | (F.col("l2") - F.col("l3") < GAP * trace))
    for i, j, k in ((1, 2, 3), (2, 1, 3), (3, 1, 2)):
        li, lj, lk = (F.col(f"l{n}") for n in (i, j, k))
        first = F.try_divide((li - F.col("_u1")) * (li - F.col("_u2")), (li - lj) * (li - lk))
        df = df.withColumn(f"alpha{i}", F.when(~F.col("degenerate"), F.acos(F.sqrt(F.least(F.lit(1.0), F.greatest(F.lit(0.0), first))))))
    return df.drop("_u1", "_u2")


def pseudo_probabilities(df: DataFrame) -> DataFrame:
    """Adds p1..p3 and ``valid``; a pixel without power is invalid."""
    trace = F.col("l1") + F.col("l2") + F.col("l3")
    df = df.withColumn("valid", trace > EPS)
    return df.withColumns({f"p{i}": F.when(F.col("valid"), F.try_divide(F.col(f"l{i}"), trace)) for i in (1, 2, 3)})


def entropy(p: list[Column], n: int = 3) -> Column:
    """Entropy of pseudo-probabilities with logarithms to the base n; 0 log 0 is 0."""
    return sum((F.when(x > 0, -x * F.ln(F.when(x > 0, x).otherwise(F.lit(1.0)))).otherwise(F.lit(0.0)) for x in p), F.lit(0.0)) / math.log(n)


def anisotropy(l2: Column, l3: Column, least: Column | float = EPS) -> Column:
    """Relative difference of the smaller eigenvalues; 0 where their sum does not exceed ``least``."""
    return F.when(l2 + l3 > least, (l2 - l3) / F.when(l2 + l3 > least, l2 + l3).otherwise(F.lit(1.0))).otherwise(F.lit(0.0))


def barrier(df: DataFrame) -> DataFrame:
    """The same rows through a generator of one row: filters on computed columns stay above it, where otherwise each
    use of a column in a filter would repeat all that it is computed from."""
    return df.select(F.inline(F.array(F.struct(*df.columns))))


def mean_alpha() -> Column:
    return F.col("p1") * F.col("alpha1") + F.col("p2") * F.col("alpha2") + F.col("p3") * F.col("alpha3")


def eigenvector_angles(df: DataFrame) -> DataFrame:
    """Adds beta, delta, gamma (mean angles weighted by p1..p3) and ``turned``: whether every eigenvector's second and third component has
    an imaginary part, so that their phases have a definite sign.  The projector on an eigenvector is a polynomial of the matrix; its first column
    gives the phases against the first component, its diagonal the moduli.  Needs l1..l3, p1..p3, ``degenerate``; columns only."""
    t12, t13, t23 = (Cx(F.col(f"t{ij}r"), F.col(f"t{ij}i")) for ij in ("12", "13", "23"))
    t11, t22, t33 = (F.col(f"t{i}{i}") for i in (1, 2, 3))
    t21, t31, t32 = t12.conj(), t13.conj(), t23.conj()
    square = {"22": t12.power() + t22 * t22 + t23.power(), "33": t13.power() + t23.power() + t33 * t33}
    square |= {"21": t21.scale(t11 + t22) + t23 * t31, "31": t31.scale(t11 + t33) + t32 * t21}
    names = {}
    for i, j, k in ((1, 2, 3), (2, 1, 3), (3, 1, 2)):
        li, lj, lk = (F.col(f"l{n}") for n in (i, j, k))
        sign = F.signum((li - lj) * (li - lk))
        for at, own in (("22", t22), ("33", t33)):
            names[f"_m{at}_{i}"] = F.sqrt(F.greatest(F.lit(0.0), (square[at] - own * (lj + lk) + lj * lk) * sign))
        for at, own in (("21", t21), ("31", t31)):
            entry = (square[at] - own.scale(lj + lk)).scale(sign)
            names |= {f"_r{at}_{i}": entry.re, f"_i{at}_{i}": entry.im}
    out = barrier(df.withColumns(names))
    trace = F.col("l1") + F.col("l2") + F.col("l3")
    mean = lambda part: sum((F.col(f"p{i}") * part(i) for i in (1, 2, 3)), F.lit(0.0))
    turned = [F.abs(F.col(f"_i{at}_{i}")) > GAP * trace * trace for at in ("21", "31") for i in (1, 2, 3)]
    out = out.withColumns({
        "beta": mean(lambda i: F.atan2(F.col(f"_m33_{i}"), F.col(f"_m22_{i}"))), "delta": mean(lambda i: F.atan2(F.col(f"_i21_{i}"), F.col(f"_r21_{i}"))),
        "gamma": mean(lambda i: F.atan2(F.col(f"_i31_{i}"), F.col(f"_r31_{i}"))), "turned": ~F.col("degenerate") & functools.reduce(lambda a, b: a & b, turned),
    })
    return barrier(out.drop(*names))


def mean_target(phi: Column | float = 0.0) -> dict[str, Column]:
    """The mean unit target vector of the mean angles alpha, beta, delta, gamma (and an absolute phase): u1_re .. u3_im."""
    alpha, beta, turn = F.col("alpha"), F.col("beta"), F.lit(phi) if isinstance(phi, float) else phi
    size = (F.cos(alpha), F.sin(alpha) * F.cos(beta), F.sin(alpha) * F.sin(beta))
    phase = (turn, turn + F.col("delta"), turn + F.col("gamma"))
    return {f"u{i}_{part}": r * f(a) for i, (r, a) in enumerate(zip(size, phase), 1) for part, f in (("re", F.cos), ("im", F.sin))}


def mechanism(alpha: Column, low_deg: float = 40.0, high_deg: float = 50.0) -> Column:
    """surface, volume or double bounce by low, middle or high mean alpha."""
    return F.when(alpha < math.radians(low_deg), "surface").when(alpha <= math.radians(high_deg), "volume").otherwise("double")


def entropy_class(h: Column, low: float = 0.5, high: float = 0.9) -> Column:
    return F.when(h < low, "point").when(h < high, "mixed").otherwise("noise")


def roll(px: DataFrame, theta: float) -> DataFrame:
    """Rotate reciprocal channels about the line of sight: the Pauli components 2 and 3 turn by twice the angle."""
    hh, hv, vv = map(Cx.of, ("hh", "hv", "vv"))
    c, s = math.cos(2 * theta), math.sin(2 * theta)
    total, diff, cross = hh + vv, hh - vv, hv.scale(2.0)
    d, x = diff.scale(c) + cross.scale(s), cross.scale(c) - diff.scale(s)
    new_hh, new_vv, new_hv = (total + d).scale(0.5), (total - d).scale(0.5), x.scale(0.5)
    return px.withColumns({f"{n}_{p}": getattr(v, p) for n, v in (("hh", new_hh), ("vv", new_vv), ("hv", new_hv), ("vh", new_hv)) for p in ("re", "im")})


def _matrix(batch: pa.RecordBatch, n: int) -> np.ndarray:
    get = lambda name: batch.column(batch.schema.get_field_index(name)).to_numpy(zero_copy_only=False)
    t = np.zeros((batch.num_rows, n, n), complex)
    for i in range(1, n + 1):
        t[:, i - 1, i - 1] = get(f"t{i}{i}")
        for j in range(i + 1, n + 1):
            t[:, i - 1, j - 1] = get(f"t{i}{j}r") + 1j * get(f"t{i}{j}i")
            t[:, j - 1, i - 1] = t[:, i - 1, j - 1].conj()
    return t


def angles_of(t: np.ndarray) -> dict[str, np.ndarray]:
    """Eigenvalues (falling), pseudo-probabilities, entropy and the weighted eigenvector angles of Hermitian matrices."""
    n = t.shape[-1]
    values, vectors = np.linalg.eigh(t)
    values, vectors = np.clip(values[:, ::-1], 0, None), vectors[:, :, ::-1]
    total = values.sum(1, keepdims=True)
    p = np.divide(values, total, out=np.zeros_like(values), where=total > EPS)
    out = {f"l{i + 1}": values[:, i] for i in range(n)}
    logs = np.log(np.where(p > 0, p, 1)) / math.log(n)
    out["h"] = -(p * logs).sum(1)
    u = np.abs(vectors)
    alpha = np.arccos(np.clip(u[:, 0], 0, 1))
    out["alpha"] = (p * alpha).sum(1)
    phase = np.angle(vectors * np.exp(-1j * np.angle(vectors[:, :1])))
    out["beta"] = (p * np.arctan2(u[:, 2], u[:, 1])).sum(1)
    out["delta"], out["gamma"] = (p * phase[:, 1]).sum(1), (p * phase[:, 2]).sum(1)
    out["phi"] = (p * np.angle(vectors[:, 0])).sum(1)
    low = values[:, 1] + values[:, 2]
    out["a"] = np.divide(values[:, 1] - values[:, 2], low, out=np.zeros_like(low), where=low > EPS)
    return out


def angles(df: DataFrame, n_dim: int = 3, keep: tuple[str, ...] = ("product_id", "row", "col")) -> DataFrame:
    """Eigen-decomposition in numpy, a batch at a time: l1.., h, alpha, beta, delta, gamma, phi, a."""
    names = [*(f"l{i}" for i in range(1, n_dim + 1)), "h", "alpha", "beta", "delta", "gamma", "phi", "a"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = angles_of(_matrix(batch, n_dim))
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(k)) for k in keep), *(pa.array(out[n]) for n in names)], names=[*keep, *names])

    kinds = dict(df.dtypes)
    return df.mapInArrow(run, ", ".join([*(f"{k} {kinds[k]}" for k in keep), *(f"{n} double" for n in names)]))
