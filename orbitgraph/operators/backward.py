"""Distributed reverse pass: every rank differentiates its own block, gradients of received rows go back to their
owners (the reverse of the halo), parameter gradients add up over ranks.

The network here is a stack of node blocks on fixed edge rows with an invariant scalar head; the loss is the squared
difference of the summed head from a target. Activations are recomputed rank by rank, so memory stays that of a block.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import layers, reverse
from ..functions.layers import Shape
from . import exchange, model
from .graph import EDGE_KEY

PARTS = "kind string, name string, atom_id long, value array<double>"
Params = list[dict[str, np.ndarray]]


def _back(shape: Shape, params: dict[str, np.ndarray]) -> Callable[[tuple, pd.DataFrame, pd.DataFrame], pd.DataFrame]:
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        edges = model._ordered(edges)
        src, dst = model._pointers(nodes, edges)
        own = np.flatnonzero(nodes["local"].to_numpy())
        grad = np.array(nodes["grad"].iloc[own].tolist(), float).reshape(len(own), shape.rows, shape.channels)
        back, _, found = reverse.node_update_back(model._rows(nodes, shape), layers.radial(edges["r"].to_numpy(), shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), own, params, shape, grad)
        node_rows = pd.DataFrame({"kind": "node", "name": None, "atom_id": nodes["atom_id"], "value": list(back.reshape(len(nodes), -1))})
        param_rows = pd.DataFrame({"kind": "param", "name": list(found), "atom_id": -1, "value": [v.ravel() for v in found.values()]})
        return pd.concat([node_rows, param_rows], ignore_index=True)

    return run


def vector_sum(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """Element-wise sums of arrays for keys that few ranks hold (nodes: their owner and its neighbours), so that the lists are
    short; sums over all ranks go by name and place (:func:`named_sums`)."""
    lists = df.groupBy(*keys).agg(F.collect_list(value).alias("_l"))
    total = F.aggregate(F.slice("_l", 2, F.size("_l")), F.get("_l", F.lit(0)), lambda s, x: F.zip_with(s, x, lambda a, b: a + b))
    return lists.select(*keys, total.alias(value))


def loss_and_gradient(
    atoms: DataFrame, edges: DataFrame, ranks: DataFrame, shape: Shape, params: Params, head: np.ndarray, target: float, species: list[int], settle: Callable[[DataFrame], DataFrame] | None = None
) -> tuple[float, Params, np.ndarray]:
    """Loss, gradients of every block's parameters, and of the head."""
    settle = settle or (lambda df: df.checkpoint())
    plan = settle(exchange.plan(edges, ranks))
    placed = settle(exchange.place_edges(edges, ranks).select(*EDGE_KEY, "dx", "dy", "dz", "r", "rank", F.lit(None).cast("array<double>").alias("emb")))
    own = ranks.select("rank", "atom_id")

    def view(nodes: DataFrame, columns: list[str]) -> DataFrame:
        mine = own.join(nodes, "atom_id").select("rank", "atom_id", *columns, F.lit(True).alias("local"))
        far = exchange.halo(nodes, plan, ["emb"]).withColumn("local", F.lit(False))
        return mine.unionByName(far, allowMissingColumns=True)

    states = [settle(model.initial_nodes(atoms, shape, species))]
    for p in params:
        states.append(settle(view(states[-1], ["emb"]).groupBy("rank").cogroup(placed.groupBy("rank")).applyInPandas(model._node_block(shape, p), model.NODE_SCHEMA)))
    row = F.slice("emb", 1, shape.channels)
    sums = states[-1].agg(*(F.sum(F.get(row, F.lit(i))).alias(f"s{i}") for i in range(shape.channels))).first()
    total = np.array([sums[f"s{i}"] for i in range(shape.channels)])
    miss = float(total @ head) - target
    first = F.array(*(F.lit(float(2 * miss * w)) for w in head))
    grads = states[-1].select("atom_id", F.concat(first, F.array_repeat(F.lit(0.0), (shape.rows - 1) * shape.channels)).alias("grad"))
    found: Params = []
    for nodes, p in zip(reversed(states[:-1]), reversed(params), strict=True):
        with_grad = view(nodes.join(grads, "atom_id"), ["emb", "grad"])
        parts = settle(with_grad.groupBy("rank").cogroup(placed.groupBy("rank")).applyInPandas(_back(shape, p), PARTS))
        summed = {k: v.reshape(p[k].shape) for k, v in named_sums(parts.where("kind = 'param'")).items()}
        found.insert(0, {k: summed.get(k, np.zeros_like(v)) for k, v in p.items()})
        grads = settle(vector_sum(parts.where("kind = 'node'").select("atom_id", F.col("value").alias("grad")), ["atom_id"], "grad"))
    return miss * miss, found, 2 * miss * total


def named_sums(rows: DataFrame) -> dict[str, np.ndarray]:
    """Sums of arrays by name and place, combined within each task: only as many numbers as there are parameters move."""
    flat = rows.select("name", F.posexplode("value").alias("pos", "v")).groupBy("name", "pos").agg(F.sum("v").alias("v"))
    out: dict[str, list[float]] = {}
    for r in flat.orderBy("name", "pos").collect():
        out.setdefault(r.name, []).append(r.v)
    return {k: np.array(v) for k, v in out.items()}


def fit(
    atoms: DataFrame, edges: DataFrame, ranks: DataFrame, shape: Shape, params: Params, head: np.ndarray, target: float, species: list[int], steps: int, lr: float = 0.02, settle: Callable[[DataFrame], DataFrame] | None = None
) -> tuple[Params, np.ndarray, list[float]]:
    """Full-batch steps (Adam) on all parameters with the plateau schedule; returns them and the losses."""
    from .telemetry import PlateauSchedule

    schedule = PlateauSchedule(lr=lr)
    flat = lambda ps, h: {**{(i, k): v for i, p in enumerate(ps) for k, v in p.items()}, (-1, "head"): h}
    values = {k: v.copy() for k, v in flat(params, head).items()}
    first, second = ({k: np.zeros_like(v) for k, v in values.items()} for _ in range(2))
    losses = []
    for t in range(1, steps + 1):
        now = [{k: values[i, k] for k in p} for i, p in enumerate(params)]
        loss, grads, grad_head = loss_and_gradient(atoms, edges, ranks, shape, now, values[-1, "head"], target, species, settle)
        losses.append(loss)
        rate = schedule.step(loss)
        for k, g in flat(grads, grad_head).items():
            first[k] = 0.9 * first[k] + 0.1 * g
            second[k] = 0.999 * second[k] + 0.001 * g * g
            values[k] = values[k] - rate * (first[k] / (1 - 0.9**t)) / (np.sqrt(second[k] / (1 - 0.999**t)) + 1e-8)
    return [{k: values[i, k] for k in p} for i, p in enumerate(params)], values[-1, "head"], losses
