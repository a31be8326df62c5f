"""Training of the equivariant linear heads on network features: Gram matrices or gradients, one partial sum a rank.

The features come from the seeded network; heads map the rows of order L to the coupled block components of order L,
channel by channel, so predictions turn with the structure. Loss: mean absolute plus mean squared difference.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.layers import Shape
from .telemetry import PlateauSchedule

PARTIAL = "head string, name string, value array<double>"


def features(rows: DataFrame, targets: DataFrame, keys: list[str], shape: Shape) -> DataFrame:
    """(head, x, y): one row for each target component. targets: keys, head, l (order), m (0..2l), y."""
    joined = targets.join(rows.select(*keys, "emb"), keys)
    x = F.slice("emb", (F.col("l") * F.col("l") + F.col("m")) * shape.channels + 1, F.lit(shape.channels))
    return joined.select("head", x.alias("x"), "y")


def _partial_sums(kind: str, weights: dict[str, np.ndarray] | None = None):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        sums: dict[tuple[str, str], np.ndarray] = {}

        def add(head: str, name: str, value: np.ndarray) -> None:
            sums[head, name] = sums.get((head, name), 0) + np.asarray(value, float).ravel()

        for frame in frames:
            for head, g in frame.groupby("head", sort=True):
                x, y = np.array(g["x"].tolist(), float), g["y"].to_numpy(float)
                if kind == "gram":
                    add(head, "xx", x.T @ x)
                    add(head, "xy", x.T @ y)
                else:
                    e = x @ weights[head] - y
                    add(head, "g1", x.T @ np.sign(e))
                    add(head, "g2", 2 * x.T @ e)
                    add(head, "l1", [np.abs(e).sum()])
                    add(head, "l2", [(e * e).sum()])
                add(head, "n", [len(y)])
        if sums:
            yield pd.DataFrame({"head": [k[0] for k in sums], "name": [k[1] for k in sums], "value": list(sums.values())})

    return run


def _reduced(partial: DataFrame) -> dict[tuple[str, str], np.ndarray]:
    """Sums over tasks; as many numbers as there are parameters (squared, for Gram matrices) reach the driver."""
    flat = partial.select("head", "name", F.posexplode("value").alias("pos", "v")).groupBy("head", "name", "pos").agg(F.sum("v").alias("v"))
    out: dict[tuple[str, str], list] = {}
    for r in flat.orderBy("head", "name", "pos").collect():
        out.setdefault((r.head, r.name), []).append(r.v)
    return {k: np.array(v) for k, v in out.items()}


def fit_least_squares(data: DataFrame, ridge: float = 1e-8) -> dict[str, np.ndarray]:
    """Closed-form heads from one pass of Gram matrices."""
    return solve(_reduced(data.mapInPandas(_partial_sums("gram"), PARTIAL)), ridge)


def solve(s: dict[tuple[str, str], np.ndarray], ridge: float = 1e-8) -> dict[str, np.ndarray]:
    """Heads from sums by (head, xx or xy)."""
    heads = sorted({k[0] for k in s})
    out = {}
    for h in heads:
        xy = s[h, "xy"]
        xx = s[h, "xx"].reshape(len(xy), len(xy))
        out[h] = np.linalg.solve(xx + ridge * (np.trace(xx) / len(xy) + 1e-12) * np.eye(len(xy)), xy)
    return out


def loss_and_gradient(data: DataFrame, weights: dict[str, np.ndarray], w1: float = 1.0, w2: float = 1.0) -> tuple[float, dict[str, np.ndarray]]:
    s = _reduced(data.mapInPandas(_partial_sums("gradient", weights), PARTIAL))
    n = sum(float(v[0]) for (_, name), v in s.items() if name == "n")
    loss = sum(w1 * float(v[0]) if name == "l1" else w2 * float(v[0]) if name == "l2" else 0.0 for (_, name), v in s.items()) / n
    return loss, {h: (w1 * s[h, "g1"] + w2 * s[h, "g2"]) / n for h in weights if (h, "g1") in s}


def fit(data: DataFrame, steps: int, schedule: PlateauSchedule | None = None, start: dict[str, np.ndarray] | None = None, channels: int | None = None) -> tuple[dict[str, np.ndarray], list[float]]:
    """Full-batch gradient steps (Adam) with a plateau schedule; returns the heads and the losses."""
    schedule = schedule or PlateauSchedule(lr=0.05)
    heads = [r.head for r in data.select("head").distinct().orderBy("head").collect()]
    size = channels or len(data.first().x)
    w = {h: (start or {}).get(h, np.zeros(size)).copy() for h in heads}
    m, v = ({h: np.zeros(size) for h in heads} for _ in range(2))
    losses = []
    for t in range(1, steps + 1):
        loss, grad = loss_and_gradient(data, w)
        losses.append(loss)
        lr = schedule.step(loss)
        for h, g in grad.items():
            m[h], v[h] = 0.9 * m[h] + 0.1 * g, 0.999 * v[h] + 0.001 * g * g
            w[h] -= lr * (m[h] / (1 - 0.9**t)) / (np.sqrt(v[h] / (1 - 0.999**t)) + 1e-8)
    return w, losses


def predict(data: DataFrame, weights: dict[str, np.ndarray]) -> DataFrame:
    """(head, y, p): predictions as column expressions, no Python."""
    table = F.create_map(*(x for h, w in sorted(weights.items()) for x in (F.lit(h), F.array(*(F.lit(float(v)) for v in w)))))
    p = F.aggregate(F.zip_with("x", F.element_at(table, F.col("head")), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return data.select("head", "y", p.alias("p"))


# order of the p elements (x, y, z = 1, 2, 3) along the spherical rows m = -1, 0, 1
P_ORDER = (2, 3, 1)
EDGE_KEYS = ["src", "dst", "sx", "sy", "sz"]


def coupled_targets(elements: DataFrame) -> DataFrame:
    """Coupled components (keys, part, l, m, y) of s,p blocks: ss, sp, ps and pp, each under a head of its own for every
    ordered pair of species. elements: keys, z1, z2, a, b, val."""
    from . import hamiltonian

    block = elements.groupBy(*EDGE_KEYS, "z1", "z2").agg(F.sort_array(F.collect_list(F.struct("a", "b", "val"))).alias("s"))
    v = lambda a, b: F.get(F.col("s"), F.lit(4 * a + b))["val"]
    pp = hamiltonian.couple_pp(F.array(*(v(a, b) for a in (1, 2, 3) for b in (1, 2, 3))))
    block = block.withColumn("pp", pp)
    entry = lambda part, l, m, y: F.struct(F.lit(part).alias("part"), F.lit(l).alias("l"), F.lit(m).alias("m"), y.alias("y"))  # noqa: E731, E741
    rows = [entry("ss", 0, 0, v(0, 0))]
    rows += [entry("sp", 1, m, v(0, b)) for m, b in enumerate(P_ORDER)] + [entry("ps", 1, m, v(a, 0)) for m, a in enumerate(P_ORDER)]
    rows += [entry("pp", l, m, F.get("pp", F.lit(i))) for l, m, i in PP_ORDER]  # noqa: E741
    out = block.where(F.size("s") == 16).select(*EDGE_KEYS, "z1", "z2", F.inline(F.array(*rows)))
    return out.withColumn("head", F.concat_ws("-", "part", "z1", "z2", "l"))


#: (l, m, place in the coupled vector): its L=1 entries are x, y, z
PP_ORDER = [(0, 0, 0), (1, 0, 2), (1, 1, 3), (1, 2, 1), *((2, k, 4 + k) for k in range(5))]


def predicted_elements(rows: DataFrame, targets: DataFrame, weights: dict[str, np.ndarray], shape: Shape) -> DataFrame:
    """(keys, a, b, p): elements predicted from edge rows, back from the coupled basis. Heads unknown to ``weights`` give 0."""
    from . import hamiltonian

    joined = targets.join(rows.select(*EDGE_KEYS, "emb"), EDGE_KEYS)
    x = F.slice("emb", (F.col("l") * F.col("l") + F.col("m")) * shape.channels + 1, F.lit(shape.channels))
    table = F.create_map(*(c for h, w in sorted(weights.items()) for c in (F.lit(h), F.array(*(F.lit(float(v)) for v in w)))))
    p = F.aggregate(F.zip_with(x, F.coalesce(F.try_element_at(table, F.col("head")), F.array_repeat(F.lit(0.0), shape.channels)), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)
    place = F.concat_ws("", "part", "l", "m")
    block = joined.select(*EDGE_KEYS, place.alias("k"), p.alias("p")).groupBy(*EDGE_KEYS).agg(F.map_from_entries(F.collect_list(F.struct("k", "p"))).alias("m"))
    get = lambda k: F.try_element_at(F.col("m"), F.lit(k))
    by_place = {i: get(f"pp{l}{m}") for l, m, i in PP_ORDER}  # noqa: E741
    block = block.withColumn("u", hamiltonian.uncouple_pp(F.array(*(by_place[i] for i in range(9)))))
    cell = lambda a, b, v: F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), v.alias("p"))
    cells = [cell(0, 0, get("ss00"))] + [cell(0, b, get(f"sp1{m}")) for m, b in enumerate(P_ORDER)] + [cell(a, 0, get(f"ps1{m}")) for m, a in enumerate(P_ORDER)]
    cells += [cell(a, b, F.get("u", F.lit(3 * (a - 1) + b - 1))) for a in (1, 2, 3) for b in (1, 2, 3)]
    return block.select(*EDGE_KEYS, F.inline(F.array(*cells)))
