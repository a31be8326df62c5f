"""Training of the whole network on blocks of the matrix: node and edge heads in the coupled basis, a loss of absolute and
squared differences over all elements, and the distributed reverse pass through edge and node blocks of every layer.

Every rank holds the edges of its destinations, with the rows they had before each layer, and its own nodes; a block's
forward and reverse pass are one exchange of node rows each. Gradients of received rows return to their owners; those of
parameters add up over ranks, element by element, before they reach the driver.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import layers, reverse
from ..functions.layers import Shape
from . import basis, exchange, model
from .backward import named_sums, vector_sum
from .graph import EDGE_KEY
from .telemetry import PlateauSchedule

Params = dict[str, np.ndarray]
EDGE = "src long, dst long, sx int, sy int, sz int, dx double, dy double, dz double, r double, rank int, z1 int, z2 int, y array<double>"
MIXED = "kind string, name string, atom_id long, value array<double>, "
EDGE_COLUMNS = [c.split()[0] for c in EDGE.split(", ")]


@lru_cache(maxsize=64)
def layout(z1: int, z2: int) -> tuple[tuple[int, tuple[tuple[int, int], ...]], ...]:
    """Orders of the components of a pair of species, each with its pairs of shells: a target holds, order by order, row by
    row, the value of every pair."""
    by: dict[int, list[tuple[int, int]]] = {}
    for _, _, i, j, _, _, order, _ in basis.components(tuple(sorted({z1, z2}))) if z1 != z2 else basis.components((z1,)):
        by.setdefault(order, [])
    for a, b, i, j, _, _, order, _ in basis.components(tuple(sorted({z1, z2}))):
        if (a, b) == (z1, z2):
            by.setdefault(order, []).append((i, j))
    return tuple((order, tuple(sorted(pairs))) for order, pairs in sorted(by.items()) if pairs)


def initial(shape: Shape, species: tuple[int, ...], n_layers: int, seed: int = 1, feed_forward: bool = True) -> Params:
    """Seeded parameters of all blocks under names "layer.kind.name", and heads of zeros."""
    out: Params = {}
    for k in range(1, n_layers + 1):
        for kind, offset in (("node", 0), ("edge", 1)):
            block = layers.block_params(shape, seed * 1000 + 2 * k + offset, feed_forward and kind == "node")
            out |= {f"{k}.{kind}.{name}": v for name, v in block.items() if kind == "node" or name != "attention"}
    for z1 in species:
        for order, pairs in layout(z1, z1):
            out[f"0.nodehead.{z1}.{order}"] = np.zeros((shape.channels + (order == 0), len(pairs)))
        for z2 in species:
            for order, pairs in layout(z1, z2):
                out[f"0.edgehead.{z1}.{z2}.{order}"] = np.zeros((shape.channels, len(pairs)))
    return out


def block_of(params: Params, layer: int, kind: str) -> Params:
    head = f"{layer}.{kind}."
    return {k[len(head) :]: v for k, v in params.items() if k.startswith(head)}


def n_layers(params: Params) -> int:
    return max(int(k.split(".")[0]) for k in params)


def targets(components: DataFrame, keys: list[str]) -> DataFrame:
    """(keys, y): the components of each block in the order of :func:`layout`."""
    rows = components.groupBy(*keys).agg(F.sort_array(F.collect_list(F.struct("L", "M", "i", "j", "y"))).alias("s"))
    return rows.select(*keys, F.transform("s", lambda x: x["y"]).alias("y"))


def _rows(values: pd.Series, shape: Shape) -> np.ndarray:
    return np.array(values.tolist(), float).reshape(len(values), shape.rows, shape.channels)


def _state(edges: pd.DataFrame, k: int, shape: Shape) -> np.ndarray:
    return layers.radial(edges["r"].to_numpy(), shape) if k == 0 else _rows(edges[f"e{k}"], shape)


def _schema(states: int, grad: bool = False) -> str:
    return EDGE + "".join(f", e{k} array<double>" for k in range(1, states + 1)) + (", grad array<double>" if grad else "")


def _features(emb: np.ndarray, order: int, constant: bool) -> np.ndarray:
    """Rows of one order; a node's invariant row gets a constant beside its channels."""
    x = emb[:, order * order : (order + 1) ** 2]
    return np.concatenate([x, np.ones((*x.shape[:2], 1))], axis=2) if constant and order == 0 else x


def _heads(emb: np.ndarray, kinds: list[tuple], y: list | None, params: Params, node: bool) -> Iterator[tuple]:
    """(name, rows, features, target, prediction) of each head over the rows of each kind of block."""
    for kind in sorted(set(kinds)):
        rows = np.array([i for i, k in enumerate(kinds) if k == kind])
        want = np.array([y[i] for i in rows], float) if y is not None else None
        at = 0
        for order, pairs in layout(*(kind * 2 if node else kind)):
            name = f"0.{'node' if node else 'edge'}head.{'.'.join(map(str, kind))}.{order}"
            x = _features(emb[rows], order, node)
            size = (2 * order + 1) * len(pairs)
            target = want[:, at : at + size].reshape(len(rows), 2 * order + 1, len(pairs)) if want is not None else None
            at += size
            yield name, rows, order, x, target, x @ params[name]


def _kinds(frame: pd.DataFrame, node: bool) -> list[tuple]:
    return [(int(z),) for z in frame["z"]] if node else [(int(a), int(b)) for a, b in zip(frame["z1"], frame["z2"], strict=True)]


def _param_rows(found: dict[str, np.ndarray], kind: str = "param") -> pd.DataFrame:
    return pd.DataFrame({"kind": kind, "name": list(found), "atom_id": -1, "value": [np.asarray(v, float).ravel() for v in found.values()]})


def _node_rows(ids: np.ndarray, grad: np.ndarray) -> pd.DataFrame:
    return pd.DataFrame({"kind": "node", "name": None, "atom_id": ids, "value": list(grad.reshape(len(ids), -1))})


def _edge_rows(edges: pd.DataFrame, states: int, grad: np.ndarray) -> pd.DataFrame:
    kept = edges[[*EDGE_COLUMNS, *(f"e{k}" for k in range(1, states + 1))]].copy()
    return kept.assign(kind="edge", name=None, atom_id=-1, value=None, grad=list(grad.reshape(len(edges), -1)))


def _mixed(parts: list[pd.DataFrame], states: int) -> pd.DataFrame:
    names = [c.split()[0] for c in (MIXED + _schema(states, True)).split(", ")]
    out = pd.concat(parts, ignore_index=True).reindex(columns=names)
    ints = [c for c in ("src", "dst", "sx", "sy", "sz", "rank", "z1", "z2") if c in out]
    out[ints] = out[ints].astype("Int64")
    return out.astype(object).where(out.notna(), None) if len(out) else out


def _loss(shape: Shape, params: Params, w1: float, w2: float, total: float, states: int):
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        sums, found, parts = {}, {}, []
        edges = model._ordered(edges)
        for node, frame, emb in ((True, nodes, _rows(nodes["emb"], shape)), (False, edges, _state(edges, states, shape) if len(edges) else np.zeros((0, shape.rows, shape.channels)))):
            grad, what = np.zeros_like(emb), "node" if node else "edge"
            for name, rows, order, x, target, p in _heads(emb, _kinds(frame, node), frame["y"].tolist(), params, node):
                e = p - target
                de = (w1 * np.sign(e) + 2 * w2 * e) / total
                found[name] = np.einsum("nmc,nmp->cp", x, de)
                grad[rows, order * order : (order + 1) ** 2] += (de @ params[name].T)[:, :, : shape.channels]
                for k, v in (("l1", np.abs(e).sum()), ("l2", (e * e).sum()), ("n", e.size)):
                    sums[f"{what}.{k}"] = sums.get(f"{what}.{k}", 0.0) + v
            if node:
                parts.append(_node_rows(frame["atom_id"].to_numpy(), grad))
            elif len(frame):
                parts.append(_edge_rows(frame, states - 1, grad))
        return _mixed([*parts, _param_rows(found), _param_rows({k: np.array([v]) for k, v in sums.items()}, "loss")], states - 1)

    return run


def _node_back(shape: Shape, p: Params, layer: int):
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        edges = model._ordered(edges)
        src, dst = model._pointers(nodes, edges)
        own = np.flatnonzero(nodes["local"].to_numpy())
        grad = _rows(nodes["grad"].iloc[own], shape)
        back, back_edge, found = reverse.node_update_back(_rows(nodes["emb"], shape), _state(edges, layer - 1, shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), own, p, shape, grad)
        parts = [_node_rows(nodes["atom_id"].to_numpy(), back), _param_rows({f"{layer}.node.{k}": v for k, v in found.items()})]
        if layer > 1 and len(edges):
            parts.append(_edge_rows(edges, layer - 2, _rows(edges["grad"], shape) + back_edge))
        return _mixed(parts, max(layer - 2, 0))

    return run


def _edge_back(shape: Shape, p: Params, layer: int):
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        edges = model._ordered(edges)
        if not len(edges):
            return _mixed([_param_rows({})], layer - 1)
        src, dst = model._pointers(nodes, edges)
        back, back_edge, found = reverse.edge_update_back(_rows(nodes["emb"], shape), _state(edges, layer - 1, shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), p, shape, _rows(edges["grad"], shape))
        return _mixed([_node_rows(nodes["atom_id"].to_numpy(), back), _param_rows({f"{layer}.edge.{k}": v for k, v in found.items()}), _edge_rows(edges, layer - 1, back_edge)], layer - 1)

    return run


def _edge_forward(shape: Shape, p: Params, layer: int):
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        names = [c.split()[0] for c in _schema(layer).split(", ")]
        if not len(edges):
            return edges.reindex(columns=names)
        edges = model._ordered(edges)
        src, dst = model._pointers(nodes, edges)
        new = layers.edge_update(_rows(nodes["emb"], shape), _state(edges, layer - 1, shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), p, shape)
        return edges.assign(**{f"e{layer}": list(new.reshape(len(edges), -1))})[names]

    return run


def _node_forward(shape: Shape, p: Params, layer: int):
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        edges = model._ordered(edges)
        src, dst = model._pointers(nodes, edges)
        own = np.flatnonzero(nodes["local"].to_numpy())
        new = layers.node_update(_rows(nodes["emb"], shape), _state(edges, layer - 1, shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), own, p, shape)
        return pd.DataFrame({"atom_id": nodes["atom_id"].to_numpy()[own], "emb": list(new.reshape(len(own), -1))})

    return run


@dataclass
class Graph:
    """A distributed structure: own atoms of each rank, the plan, edges on the rank of their destination."""

    own: DataFrame  # rank, atom_id, z, y
    plan: DataFrame
    edges: DataFrame
    start: DataFrame  # initial node rows
    settle: Callable[[DataFrame], DataFrame]
    total: float

    def view(self, nodes: DataFrame, columns: list[str]) -> DataFrame:
        mine = self.own.select("rank", "atom_id").join(nodes, "atom_id").select("rank", "atom_id", *columns, F.lit(True).alias("local"))
        far = exchange.halo(nodes, self.plan, ["emb"]).withColumn("local", F.lit(False))
        return mine.unionByName(far, allowMissingColumns=True)

    def by_rank(self, nodes: DataFrame, edges: DataFrame, f: Callable, schema: str) -> DataFrame:
        return self.settle(nodes.groupBy("rank").cogroup(edges.groupBy("rank")).applyInPandas(f, schema))


def distribute(atoms: DataFrame, edges: DataFrame, ranks: DataFrame, shape: Shape, species: tuple[int, ...], settle: Callable | None = None, node_y: DataFrame | None = None, edge_y: DataFrame | None = None) -> Graph:
    """``node_y``: atom_id, y; ``edge_y``: edge keys, y (both from :func:`targets`); without them the graph is for prediction."""
    settle = settle or (lambda df: df.checkpoint())
    own = ranks.select("rank", "atom_id").join(atoms.select("atom_id", F.col("species").alias("z")), "atom_id")
    own = own.join(node_y, "atom_id") if node_y is not None else own.withColumn("y", F.lit(None).cast("array<double>"))
    placed = basis.with_species(exchange.place_edges(edges, ranks).select(*EDGE_KEY, "dx", "dy", "dz", "r", "rank"), atoms)
    placed = placed.join(edge_y, list(EDGE_KEY)) if edge_y is not None else placed.withColumn("y", F.lit(None).cast("array<double>"))
    own, placed = settle(own), settle(placed.select(*EDGE_COLUMNS))
    total = sum(df.agg(F.sum(F.size("y"))).first()[0] or 0 for df in (own, placed)) if node_y is not None else 1.0
    return Graph(own, settle(exchange.plan(edges, ranks)), placed, settle(model.initial_nodes(atoms, shape, list(species))), settle, float(total))


def forward(g: Graph, params: Params, shape: Shape) -> tuple[list[DataFrame], DataFrame]:
    """Node rows after every layer, and edges with theirs."""
    nodes, edges = [g.start], g.edges
    for k in range(1, n_layers(params) + 1):
        nodes.append(g.by_rank(g.view(nodes[-1], ["emb"]), edges, _node_forward(shape, block_of(params, k, "node"), k), model.NODE_SCHEMA))
        edges = g.by_rank(g.view(nodes[-1], ["emb"]), edges, _edge_forward(shape, block_of(params, k, "edge"), k), _schema(k))
    return nodes, edges


def _summed(parts: list[DataFrame]) -> DataFrame:
    """(atom_id, grad): gradients of the ranks that hold a node, added up at its owner."""
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return vector_sum(both, ["atom_id"], "grad")


def loss_and_gradient(g: Graph, params: Params, shape: Shape, w1: float = 1.0, w2: float = 1.0, gradient: bool = True) -> tuple[dict[str, float], Params]:
    """Loss (and its parts: mean absolute error of nodes and of edges) and, unless only the loss is asked for, the gradient
    of every parameter."""
    depth = n_layers(params)
    nodes, edges = forward(g, params, shape)
    ready = g.own.join(nodes[-1], "atom_id")
    parts = g.by_rank(ready, edges, _loss(shape, params, w1, w2, g.total, depth), MIXED + _schema(depth - 1, True))
    sums = {k: float(v[0]) for k, v in named_sums(parts.where("kind = 'loss'")).items()}
    n = sums["node.n"] + sums.get("edge.n", 0.0)
    losses = {
        "loss": (w1 * (sums["node.l1"] + sums.get("edge.l1", 0.0)) + w2 * (sums["node.l2"] + sums.get("edge.l2", 0.0))) / n,
        "node_mae": sums["node.l1"] / sums["node.n"],
        "edge_mae": sums.get("edge.l1", 0.0) / max(sums.get("edge.n", 0.0), 1.0),
    }
    if not gradient:
        return losses, {}
    found = named_sums(parts.where("kind = 'param'"))
    node_grads = [parts.where("kind = 'node'").select("atom_id", F.col("value").alias("grad"))]
    cut = lambda df, states: df.where("kind = 'edge'").select(*EDGE_COLUMNS, *(f"e{k}" for k in range(1, states + 1)), "grad")
    edges = cut(parts, depth - 1)
    for k in range(depth, 0, -1):
        back = g.by_rank(g.view(nodes[k], ["emb"]), edges, _edge_back(shape, block_of(params, k, "edge"), k), MIXED + _schema(k - 1, True))
        found |= named_sums(back.where("kind = 'param'"))
        grads = g.settle(_summed([*node_grads, back.where("kind = 'node'").select("atom_id", F.col("value").alias("grad"))]))
        with_grad = g.view(nodes[k - 1].join(grads, "atom_id"), ["emb", "grad"])
        parts = g.by_rank(with_grad, cut(back, k - 1), _node_back(shape, block_of(params, k, "node"), k), MIXED + _schema(max(k - 2, 0), True))
        found |= named_sums(parts.where("kind = 'param'"))
        node_grads = [parts.where("kind = 'node'").select("atom_id", F.col("value").alias("grad"))]
        edges = cut(parts, max(k - 2, 0))
    return losses, {k: found[k].reshape(v.shape) if k in found else np.zeros_like(v) for k, v in params.items()}


def _gram(shape: Shape, params: Params, states: int, node: bool):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        found: dict[str, np.ndarray] = {}
        for frame in frames:
            if len(frame):
                emb = _rows(frame["emb"], shape) if node else _state(frame, states, shape)
                for name, _, _, x, target, _ in _heads(emb, _kinds(frame, node), frame["y"].tolist(), params, node):
                    for k, v in (("xx", np.einsum("nmc,nmd->cd", x, x)), ("xy", np.einsum("nmc,nmp->cp", x, target))):
                        found[f"{name}|{k}"] = found.get(f"{name}|{k}", 0.0) + v
        yield _param_rows(found)

    return run


def fit_heads(g: Graph, params: Params, shape: Shape, ridge: float = 1e-6) -> Params:
    """The heads of least squared error on the network as it is, from one pass of Gram matrices: a start for training."""
    nodes, edges = forward(g, params, shape)
    schema = "kind string, name string, atom_id long, value array<double>"
    depth = n_layers(params)
    sums = named_sums(g.own.join(nodes[-1], "atom_id").mapInPandas(_gram(shape, params, depth, True), schema)) | named_sums(edges.mapInPandas(_gram(shape, params, depth, False), schema))
    return solved(params, sums, ridge)


def solved(params: Params, sums: dict[str, np.ndarray], ridge: float) -> Params:
    """Parameters with the heads that Gram matrices (under "name|xx" and "name|xy") ask for."""
    out = dict(params)
    for name, v in params.items():
        if f"{name}|xx" in sums:
            xx, xy = sums[f"{name}|xx"].reshape(len(v), len(v)), sums[f"{name}|xy"].reshape(v.shape)
            out[name] = np.linalg.solve(xx + ridge * (np.trace(xx) / len(v) + 1e-12) * np.eye(len(v)), xy)
    return out


@dataclass
class Training:
    """What a stopped run needs to go on: parameters, both moments, steps done, the schedule, losses so far."""

    params: Params
    first: Params
    second: Params
    step: int
    schedule: PlateauSchedule
    losses: list[dict[str, float]]


def begin(params: Params, lr: float = 0.01) -> Training:
    zeros = lambda: {k: np.zeros_like(v) for k, v in params.items()}
    return Training(dict(params), zeros(), zeros(), 0, PlateauSchedule(lr=lr), [])


def save(spark: SparkSession, t: Training, path: str) -> None:
    """One folder for each saved step in the shared storage; it counts once its writing has finished."""
    rows = [(kind, k, list(map(int, v.shape)), v.ravel().tolist()) for kind, ps in (("param", t.params), ("first", t.first), ("second", t.second)) for k, v in ps.items()]
    s = t.schedule
    rows.append(("schedule", "", [], [s.lr, s.factor, float(s.patience), s.threshold, s.min_lr, s.best, float(s.bad)]))
    rows += [("loss", name, [], [x[name] for x in t.losses]) for name in (t.losses[0] if t.losses else ())]
    spark.createDataFrame(rows, "kind string, name string, shape array<int>, value array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/step={t.step}")


def load(spark: SparkSession, path: str) -> Training | None:
    """The last saved step, if there is one."""
    jvm = spark.sparkContext._jvm
    folder = jvm.org.apache.hadoop.fs.Path(path)
    fs = folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if not fs.exists(folder):
        return None
    done = [int(f.getPath().getName().split("=")[1]) for f in fs.listStatus(folder) if f.getPath().getName().startswith("step=") and fs.exists(jvm.org.apache.hadoop.fs.Path(f.getPath(), "_SUCCESS"))]
    if not done:
        return None
    out = Training({}, {}, {}, max(done), PlateauSchedule(), [])
    losses: dict[str, list[float]] = {}
    for r in spark.read.parquet(f"{path}/step={max(done)}").collect():  # as many numbers as there are parameters, three times
        if r.kind == "schedule":
            lr, factor, patience, threshold, min_lr, best, bad = r.value
            out.schedule = PlateauSchedule(lr, factor, int(patience), threshold, min_lr, best, int(bad))
        elif r.kind == "loss":
            losses[r.name] = list(r.value)
        else:
            {"param": out.params, "first": out.first, "second": out.second}[r.kind][r.name] = np.array(r.value).reshape(tuple(r.shape))
    out.losses = [dict(zip(losses, x, strict=True)) for x in zip(*losses.values(), strict=True)]
    return out


def fit(g: Graph, t: Training, shape: Shape, steps: int, w1: float = 1.0, w2: float = 1.0, path: str | None = None, every: int = 100) -> Training:
    """:func:`descend` on a graph of ranks."""
    return descend(g.own.sparkSession, lambda params: loss_and_gradient(g, params, shape, w1, w2), t, steps, path, every)


def descend(spark: SparkSession, gradient: Callable[[Params], tuple[dict[str, float], Params]], t: Training, steps: int, path: str | None = None, every: int = 100) -> Training:
    """Full-batch steps (Adam) up to ``steps`` in all, with the plateau schedule; a run with a ``path`` goes on from the last
    saved step there, and saves every so many steps and at the end. gradient: loss, with its parts, and gradient at parameters."""
    t = (load(spark, path) if path else None) or t
    while t.step < steps:
        losses, grads = gradient(t.params)
        t.step += 1
        t.losses.append(losses)
        rate = t.schedule.step(losses["loss"])
        for k, v in grads.items():
            t.first[k] = 0.9 * t.first[k] + 0.1 * v
            t.second[k] = 0.999 * t.second[k] + 0.001 * v * v
            t.params[k] = t.params[k] - rate * (t.first[k] / (1 - 0.9**t.step)) / (np.sqrt(t.second[k] / (1 - 0.999**t.step)) + 1e-8)
        if path and (t.step % every == 0 or t.step == steps):
            save(spark, t, path)
    return t


def _predicted(shape: Shape, params: Params, states: int, node: bool, keys: list[str] | tuple[str, ...]):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if not len(frame):
                continue
            emb = _rows(frame["emb"], shape) if node else _state(frame, states, shape)
            kinds = _kinds(frame, node)
            for name, rows, order, _, _, p in _heads(emb, kinds, None, params, node):
                z = tuple(int(x) for x in name.split(".")[2:-1]) * (2 if node else 1)
                pairs = np.array(dict(layout(*z))[order])
                n, m = len(rows), 2 * order + 1
                out = {k: np.repeat(frame[k].to_numpy()[rows], m * len(pairs)) for k in keys}
                out |= {"z1": z[0], "z2": z[1], "L": order, "M": np.tile(np.repeat(np.arange(m), len(pairs)), n)}
                out |= {"i": np.tile(pairs[:, 0], n * m), "j": np.tile(pairs[:, 1], n * m), "y": p.ravel()}
                out["l1"], out["l2"] = (np.array(basis.SHELLS[zz])[out[c]] for zz, c in zip(z, ("i", "j"), strict=True))
                yield pd.DataFrame(out)

    return run


def predict(g: Graph, params: Params, shape: Shape, species: tuple[int, ...]) -> DataFrame:
    """(kind, src, dst, sx, sy, sz, z1, z2, a, b, val): elements of all diagonal blocks and of those of the graph's edges; what
    elements there are follows from the graph and the shells alone."""
    nodes, edges = forward(g, params, shape)
    depth = n_layers(params)
    tail = ", z1 int, z2 int, L int, M int, i int, j int, y double, l1 int, l2 int"
    at = g.own.join(nodes[-1], "atom_id").mapInPandas(_predicted(shape, params, depth, True, ["atom_id"]), "atom_id long" + tail)
    off = edges.mapInPandas(_predicted(shape, params, depth, False, EDGE_KEY), "src long, dst long, sx int, sy int, sz int" + tail)
    at = at.select(F.lit("node").alias("kind"), F.col("atom_id").alias("src"), F.col("atom_id").alias("dst"), *(F.lit(0).alias(s) for s in ("sx", "sy", "sz")), "z1", "z2", "L", "M", "i", "j", "l1", "l2", "y")
    return to_elements(at.unionByName(off.select(F.lit("edge").alias("kind"), *at.columns[1:])), species)


def truth(edges: DataFrame, atoms: DataFrame, r_cut: float, species: tuple[int, ...]) -> DataFrame:
    """The stand-in's elements in the form of :func:`predict`."""
    off = basis.coupled(edges, atoms, r_cut, species).withColumn("kind", F.lit("edge"))
    at = basis.coupled_onsite(edges, atoms, r_cut, species)
    at = at.select(F.lit("node").alias("kind"), F.col("atom_id").alias("src"), F.col("atom_id").alias("dst"), *(F.lit(0).alias(s) for s in ("sx", "sy", "sz")), F.col("z").alias("z1"), F.col("z").alias("z2"), "i", "j", "l1", "l2", "L", "M", "y")
    return to_elements(at.unionByName(off.select(*at.columns)), species)


def to_elements(components: DataFrame, species: tuple[int, ...]) -> DataFrame:
    keys = ["kind", *EDGE_KEY, "z1", "z2"]
    return basis.elements(basis.uncouple(components, keys), "z1", "z2", species).select(*keys, "a", "b", "val")


def errors(predicted: DataFrame, truth_: DataFrame) -> DataFrame:
    """(kind, err, size) of every element of either side."""
    keys = ["kind", *EDGE_KEY, "a", "b"]
    both = predicted.select(*keys, F.col("val").alias("p")).join(truth_.select(*keys, F.col("val").alias("t")), keys, "full")
    return both.select("kind", F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("t", F.lit(0.0))).alias("err"), F.abs(F.coalesce("t", F.lit(0.0))).alias("size"))
