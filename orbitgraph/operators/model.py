"""The network on a distributed graph: each block is one exchange of node rows and one fused call for each rank."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import layers
from ..functions.layers import Shape
from . import exchange
from .graph import EDGE_KEY

NODE_SCHEMA = "atom_id long, emb array<double>"
EDGE_SCHEMA = "src long, dst long, sx int, sy int, sz int, dx double, dy double, dz double, r double, rank int, emb array<double>"


def species_rows(shape: Shape, species: list[int], seed: int = 1) -> dict[int, list[float]]:
    """Seeded initial embedding of each species (row l=m=0)."""
    return {z: np.random.default_rng([seed, z]).normal(size=shape.channels).tolist() for z in species}


def initial_nodes(atoms: DataFrame, shape: Shape, species: list[int], seed: int = 1) -> DataFrame:
    table = species_rows(shape, species, seed)
    first = F.element_at(F.create_map(*(x for z, v in table.items() for x in (F.lit(z), F.array(*map(F.lit, v))))), F.col("species"))
    return atoms.select("atom_id", F.concat(first, F.array_repeat(F.lit(0.0), (shape.rows - 1) * shape.channels)).alias("emb"))


def _pointers(nodes: pd.DataFrame, edges: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
    ids = pd.Index(nodes["atom_id"])
    return ids.get_indexer(edges["src"]), ids.get_indexer(edges["dst"])


def _rows(frame: pd.DataFrame, shape: Shape) -> np.ndarray:
    values = frame["emb"].tolist()
    if "packed" in frame:  # received rows came as bytes
        values = [exchange.unpacked(b, shape.precision) if b is not None else v for v, b in zip(values, frame["packed"], strict=True)]
    return np.array(values, float).reshape(len(frame), shape.rows, shape.channels)


def _edge_rows(edges: pd.DataFrame, shape: Shape) -> np.ndarray:
    if len(edges) and edges["emb"].iloc[0] is not None:
        return _rows(edges, shape)
    return layers.radial(edges["r"].to_numpy(), shape)


def _ordered(edges: pd.DataFrame) -> pd.DataFrame:
    """One order of the edges whatever their arrival, so that sums do not depend on it."""
    return edges.sort_values(["dst", "src", "sx", "sy", "sz"], kind="stable").reset_index(drop=True)


def _node_block(shape: Shape, params: dict[str, np.ndarray]) -> Callable[[tuple, pd.DataFrame, pd.DataFrame], pd.DataFrame]:
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        edges = _ordered(edges)
        src, dst = _pointers(nodes, edges)
        own = np.flatnonzero(nodes["local"].to_numpy())
        vectors = edges[["dx", "dy", "dz"]].to_numpy()
        new = layers.node_update(_rows(nodes, shape), _edge_rows(edges, shape), src, dst, vectors, own, params, shape)
        return pd.DataFrame({"atom_id": nodes["atom_id"].to_numpy()[own], "emb": list(new.reshape(len(own), -1))})

    return run


def _edge_block(shape: Shape, params: dict[str, np.ndarray]) -> Callable[[tuple, pd.DataFrame, pd.DataFrame], pd.DataFrame]:
    def run(key: tuple, nodes: pd.DataFrame, edges: pd.DataFrame) -> pd.DataFrame:
        if not len(edges):
            return edges
        edges = _ordered(edges)
        src, dst = _pointers(nodes, edges)
        new = layers.edge_update(_rows(nodes, shape), _edge_rows(edges, shape), src, dst, edges[["dx", "dy", "dz"]].to_numpy(), params, shape)
        return edges.assign(emb=list(new.reshape(len(edges), -1)))

    return run


def forward(atoms: DataFrame, edges: DataFrame, ranks: DataFrame, shape: Shape, n_layers: int, species: list[int], seed: int = 1, settle: Callable[[DataFrame], DataFrame] | None = None) -> tuple[DataFrame, DataFrame]:
    """Node rows and edge rows after ``n_layers`` layers of a node and an edge block.

    Edges stay on the rank of their destination; only the node rows of the plan travel, once a block. ``settle`` cuts
    the lineage between blocks (a reliable checkpoint by default, so lost executors cost one block at most)."""
    settle = settle or (lambda df: df.checkpoint())
    plan = settle(exchange.plan(edges, ranks))
    placed = settle(exchange.place_edges(edges, ranks).select(*EDGE_KEY, "dx", "dy", "dz", "r", "rank", F.lit(None).cast("array<double>").alias("emb")))
    nodes = initial_nodes(atoms, shape, species, seed)

    def view(nodes: DataFrame) -> DataFrame:
        own = ranks.select("rank", "atom_id").join(nodes, "atom_id").select("rank", "atom_id", "emb", F.lit(True).alias("local"))
        if shape.precision == "fp64":
            return own.unionByName(exchange.halo(nodes, plan, ["emb"]).withColumn("local", F.lit(False)))
        sent = nodes.select("atom_id", exchange.packed("emb", shape.precision).alias("packed"))
        far = exchange.halo(sent, plan, ["packed"]).withColumn("local", F.lit(False))
        return own.unionByName(far, allowMissingColumns=True)

    for layer in range(n_layers):
        node_params, edge_params = (layers.block_params(shape, seed * 1000 + 2 * layer + k) for k in (0, 1))
        nodes = settle(view(nodes).groupBy("rank").cogroup(placed.groupBy("rank")).applyInPandas(_node_block(shape, node_params), NODE_SCHEMA))
        placed = settle(view(nodes).groupBy("rank").cogroup(placed.groupBy("rank")).applyInPandas(_edge_block(shape, edge_params), EDGE_SCHEMA))
    return nodes, placed


def single_rank(atoms: DataFrame) -> DataFrame:
    return atoms.select("atom_id", F.lit(0).alias("rank"))


def energy(nodes: DataFrame, shape: Shape, weights: list[float]) -> DataFrame:
    """A scalar head: sum over atoms of a linear map of their invariant row."""
    row = F.slice("emb", 1, shape.channels)
    each = F.aggregate(F.zip_with(row, F.array(*map(F.lit, weights)), lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    return nodes.agg(F.sum(each).alias("energy"))
