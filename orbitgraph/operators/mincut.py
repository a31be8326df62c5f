"""Minimum-cut baselines: a multilevel k-way partitioner whose first levels are contracted on the executors, and balanced
label propagation.

The multilevel method contracts heavy edges by rounds of matching, splits the small graph by greedy growth, and refines
on the way back by moves of positive gain under a balance limit.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import boxes
from .structure import Cell

MAX_EDGES = 2_000_000  # undirected pairs that the driver takes; larger graphs are contracted first


def _undirected(edges: DataFrame) -> DataFrame:
    a, b = F.least("src", "dst"), F.greatest("src", "dst")
    return edges.where("src <> dst").groupBy(a.alias("a"), b.alias("b")).agg(F.count(F.lit(1)).alias("w"))


def _contract(a: np.ndarray, b: np.ndarray, w: np.ndarray, weight: np.ndarray, limit: float) -> np.ndarray:
    """New vertex of each vertex after one round of heavy-edge matching in order of falling weight."""
    n = len(weight)
    mate = np.full(n, -1)
    order = np.argsort(-w, kind="stable")
    for x, y in zip(a[order].tolist(), b[order].tolist(), strict=True):
        if mate[x] < 0 and mate[y] < 0 and weight[x] + weight[y] <= limit:
            mate[x], mate[y] = y, x
    lead = np.where((mate >= 0) & (mate < np.arange(n)), mate, np.arange(n))
    _, new = np.unique(lead, return_inverse=True)
    return new


def _merge(a: np.ndarray, b: np.ndarray, w: np.ndarray, new: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    x, y = new[a], new[b]
    keep = x != y
    x, y, w = np.minimum(x, y)[keep], np.maximum(x, y)[keep], w[keep]
    key, inverse = np.unique(x * n + y, return_inverse=True)
    return key // n, key % n, np.bincount(inverse, weights=w, minlength=len(key))


def _adjacency(a: np.ndarray, b: np.ndarray, w: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    x, y, v = np.concatenate([a, b]), np.concatenate([b, a]), np.concatenate([w, w])
    order = np.argsort(x, kind="stable")
    return np.searchsorted(x[order], np.arange(n + 1)), y[order], v[order]


def _grow(a: np.ndarray, b: np.ndarray, w: np.ndarray, weight: np.ndarray, parts: int) -> np.ndarray:
    """Parts grown one after another, always by the vertex most strongly tied to the part."""
    n = len(weight)
    start, to, v = _adjacency(a, b, w, n)
    part, left = np.full(n, -1), weight.sum()
    for k in range(parts - 1):
        goal, size = left / (parts - k), 0.0
        tie = np.zeros(n)
        free = part < 0
        pull = np.array([v[start[i] : start[i + 1]].sum() for i in range(n)])
        while size < goal and free.any():
            score = np.where(free, tie * 1e6 - pull, -np.inf)
            i = int(np.argmax(score))
            if size and size + weight[i] / 2 > goal:
                break
            part[i], size = k, size + weight[i]
            free[i] = False
            np.add.at(tie, to[start[i] : start[i + 1]], v[start[i] : start[i + 1]])
        left -= size
    part[part < 0] = parts - 1
    return part


def _refine(a: np.ndarray, b: np.ndarray, w: np.ndarray, weight: np.ndarray, part: np.ndarray, parts: int, imbalance: float, rounds: int = 8) -> np.ndarray:
    n = len(weight)
    start, to, v = _adjacency(a, b, w, n)
    size, most = np.bincount(part, weights=weight, minlength=parts), imbalance * weight.sum() / parts
    part = part.copy()
    for _ in range(rounds):
        moved = 0
        edge_vertices = np.unique(np.concatenate([a[part[a] != part[b]], b[part[a] != part[b]]]))
        for i in edge_vertices.tolist():
            tie = np.bincount(part[to[start[i] : start[i + 1]]], weights=v[start[i] : start[i + 1]], minlength=parts)
            gain = tie - tie[part[i]]
            fits = size + weight[i] <= most
            too_big = size[part[i]] > most
            gain[~fits] = -np.inf
            gain[part[i]] = -np.inf
            best = int(np.argmax(gain))
            if gain[best] > 0 or (too_big and np.isfinite(gain[best])):
                size[part[i]] -= weight[i]
                size[best] += weight[i]
                part[i] = best
                moved += 1
        if not moved:
            break
    return part


def multilevel(a: np.ndarray, b: np.ndarray, w: np.ndarray, weight: np.ndarray, parts: int, imbalance: float = 1.03, small: int = 40) -> np.ndarray:
    """Part of each vertex; a < b are undirected edges of weight w."""
    levels, graph = [], (a, b, w.astype(float), weight.astype(float))
    while len(graph[3]) > max(small, 8 * parts):
        x, y, v, size = graph
        new = _contract(x, y, v, size, 1.5 * size.sum() / max(small, 4 * parts))
        n = int(new.max()) + 1
        if n > 0.95 * len(size):
            break
        levels.append((graph, new))
        graph = (*_merge(x, y, v, new, n), np.bincount(new, weights=size))
    part = _refine(*graph, _grow(*graph, parts), parts, imbalance)
    for graph, new in reversed(levels):
        part = _refine(*graph, part[new], parts, imbalance)
    return part


def coarsen(pairs: DataFrame, homes: DataFrame, most: int, limit: int = 8, rounds: int = 12) -> tuple[DataFrame, DataFrame]:
    """Heavy-edge matching on the executors until at most ``most`` pairs are left.

    pairs: a, b, w; homes: atom_id, v. Every vertex picks its heaviest neighbour, ties by a hash of the pair; who pick one
    another become one, while they hold at most ``limit`` atoms together. Each round is an aggregate and three joins."""
    for k in range(rounds):
        if pairs.count() <= most:
            return pairs, homes
        size = homes.groupBy("v").agg(F.count(F.lit(1)).alias("size"))
        ties = pairs.select(F.col("a").alias("v"), F.col("b").alias("u"), "w").unionAll(pairs.select("b", "a", "w"))
        room = ties.join(size, "v").join(size.select(F.col("v").alias("u"), F.col("size").alias("size_u")), "u").where(F.col("size") + F.col("size_u") <= limit << k)
        mark = F.xxhash64(F.least("v", "u"), F.greatest("v", "u"), F.lit(k))
        pick = room.groupBy("v").agg(F.max(F.struct("w", mark.alias("mark"), "u")).alias("m")).select("v", F.col("m.u").alias("u")).checkpoint()
        back = pick.select(F.col("u").alias("v"), F.col("v").alias("u"))
        joined = pick.join(back, ["v", "u"]).where("v > u").select("v", F.col("u").alias("lead")).checkpoint()
        to = lambda df, c: df.join(joined.select(F.col("v").alias(c), "lead"), c, "left").withColumn(c, F.coalesce("lead", c)).drop("lead")
        homes = to(homes, "v").checkpoint()
        moved = to(to(pairs, "a"), "b").where("a <> b")
        pairs = moved.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("w").alias("w")).checkpoint()
    return pairs, homes


def min_cut(edges: DataFrame, parts: int, imbalance: float = 1.03, weight: str = "degree", max_edges: int = MAX_EDGES) -> DataFrame:
    """(atom_id, rank) of the multilevel partition. The first levels are contracted on the executors, until the graph has
    at most ``max_edges`` pairs; the driver does the rest."""
    pairs = _undirected(edges).persist()
    ends = pairs.select(F.col("a").alias("atom_id"), "w").unionAll(pairs.select("b", "w")).groupBy("atom_id").agg(F.sum("w").alias("degree"))
    homes = ends.select("atom_id", F.col("atom_id").alias("v"))
    if pairs.count() > max_edges:
        from ..session import ensure_checkpoint_dir

        ensure_checkpoint_dir(edges.sparkSession)
        pairs, homes = coarsen(pairs, homes.checkpoint(), max_edges)
        if pairs.count() > max_edges:
            raise ValueError(f"more than {max_edges} pairs are left after contraction: use label_propagation")
    each = F.col("degree") if weight == "degree" else F.lit(1)
    sizes = ends.join(homes, "atom_id").groupBy("v").agg(F.sum(each).alias("size")).orderBy("v").toArrow().to_pandas()
    table = pairs.toArrow().to_pandas().sort_values(["a", "b"])
    ids = sizes["v"].to_numpy()
    a, b, w = np.searchsorted(ids, table["a"]), np.searchsorted(ids, table["b"]), table["w"].to_numpy(float)
    part = multilevel(a, b, w, sizes["size"].to_numpy(float), parts, imbalance)
    coarse = edges.sparkSession.createDataFrame([(int(i), int(p)) for i, p in zip(ids, part, strict=True)], "v long, rank int")
    return homes.join(coarse, "v").select("atom_id", "rank")


def label_propagation(edges: DataFrame, start: DataFrame, parts: int, rounds: int = 5, imbalance: float = 1.1) -> DataFrame:
    """Distributed stand-in: each atom proposes the part most of its neighbours have; proposals are taken by falling
    gain while the part has room. Half of the atoms may move in a round, so that neighbours do not swap places."""
    ranks = start
    n = ranks.count()
    room = imbalance * n / parts
    for k in range(rounds):
        tie = edges.join(ranks.withColumnRenamed("atom_id", "src"), "src").groupBy(F.col("dst").alias("atom_id"), "rank").agg(F.count(F.lit(1)).alias("tie"))
        best = tie.groupBy("atom_id").agg(F.max(F.struct("tie", (-F.col("rank")).alias("r"))).alias("m"))
        both = ranks.join(best, "atom_id", "left").join(tie.select("atom_id", "rank", F.col("tie").alias("own")), ["atom_id", "rank"], "left")
        wish = F.when((F.col("atom_id") + k) % 2 == 0, -F.col("m.r"))
        both = both.select("atom_id", "rank", wish.alias("wish"), (F.col("m.tie") - F.coalesce("own", F.lit(0))).alias("gain"))
        size = ranks.groupBy(F.col("rank").alias("wish")).agg(F.count(F.lit(1)).alias("size"))
        line = Window.partitionBy("wish").orderBy(F.desc("gain"), "atom_id")
        asked = both.where((F.col("gain") > 0) & (F.col("wish") != F.col("rank"))).join(F.broadcast(size), "wish", "left")
        taken = asked.withColumn("n", F.row_number().over(line)).where(F.coalesce("size", F.lit(0)) + F.col("n") <= room).select("atom_id", F.col("wish").alias("to"))
        ranks = ranks.join(taken, "atom_id", "left").select("atom_id", F.coalesce("to", "rank").cast("int").alias("rank")).checkpoint()
    return ranks


DRIVER_PAIRS = 500_000  # undirected pairs of a graph that goes to the driver as it is; of larger ones clusters of atoms go


def _clusters(atoms: DataFrame, cell: Cell, r_cut: float, n_atoms: int, group: int) -> DataFrame:
    """(atom_id, lead, degree): clusters of about ``group`` atoms by rounds of heavy-edge matching inside boxes."""

    def kernel(frame, own, edges):
        ids, degree = frame["atom_id"].to_numpy(), np.zeros(len(frame), np.int64)
        place = np.full(len(frame), -1)
        place[own] = np.arange(len(own))
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for me, other in edges:
            degree += np.bincount(me[ids[me] != ids[other]], minlength=len(frame))
            inside = (place[other] >= 0) & (place[me] < place[other])
            a.append(place[me[inside]])
            b.append(place[other[inside]])
        of, size = np.arange(len(own)), np.ones(len(own))
        x, y = np.concatenate(a), np.concatenate(b)
        w = np.ones(len(x))
        while group > 1 and len(size) > len(own) / group and len(x):
            new = _contract(x, y, w, size, 1.5 * group)
            n = int(new.max()) + 1
            if n > 0.95 * len(size):
                break
            x, y, w = _merge(x, y, w, new, n)
            of, size = new[of], np.bincount(new, weights=size)
        lead = np.full(len(size), np.iinfo(np.int64).max)
        np.minimum.at(lead, of, ids[own])
        return pd.DataFrame({"atom_id": ids[own], "lead": lead[of], "degree": degree[own]})

    return boxes.over(atoms, cell, r_cut, [], kernel, "atom_id long, lead long, degree long", n_atoms)


def _cluster_pairs(atoms: DataFrame, cell: Cell, r_cut: float, n_atoms: int) -> DataFrame:
    """(src, dst, sx, sy, sz, w): edges between clusters (column ``lead`` of the atoms), by image."""

    def kernel(frame, own, edges):
        names, of = np.unique(frame["lead"].to_numpy(), return_inverse=True)
        shifts, kind = np.unique(frame[["sx", "sy", "sz"]].to_numpy(np.int64), axis=0, return_inverse=True)
        kind, home, codes, counts = kind.ravel(), (shifts == 0).all(1), [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for me, other in edges:
            apart = (of[me] != of[other]) | ~home[kind[other]]
            code, k = np.unique((of[me[apart]] * len(names) + of[other[apart]]) * len(shifts) + kind[other[apart]], return_counts=True)
            codes.append(code)
            counts.append(k)
        code, where = np.unique(np.concatenate(codes), return_inverse=True)
        w = np.bincount(where, weights=np.concatenate(counts), minlength=len(code)).astype(np.int64)
        pair, s = code // len(shifts), shifts[code % len(shifts)]
        return pd.DataFrame({"src": names[pair // len(names)], "dst": names[pair % len(names)], "sx": s[:, 0], "sy": s[:, 1], "sz": s[:, 2], "w": w})

    each = boxes.over(atoms, cell, r_cut, ["lead"], kernel, "src long, dst long, sx int, sy int, sz int, w long", n_atoms)
    return each.groupBy("src", "dst", "sx", "sy", "sz").agg(F.sum("w").alias("w"))


def min_cut_boxes(atoms: DataFrame, cell: Cell, r_cut: float, n_atoms: int, parts: tuple[int, ...], tiles: tuple[int, int, int] = (1, 1, 1), imbalance: float = 1.03, most: int = DRIVER_PAIRS) -> DataFrame:
    """(atom_id, ranks) of the multilevel partition of a radius graph that never exists as a table, for several numbers of
    parts at once and, within each, for each tile of a tiled structure.

    Atoms are matched inside boxes on the executors, until about ``most`` pairs of clusters are left; the driver splits and
    refines the graph of clusters. A graph that is small enough goes there atom by atom."""
    k, degree = math.prod(tiles), boxes.degree(atoms, cell, r_cut, n_atoms)
    group = 1
    if (degree.agg(F.sum("n_in")).first()[0] or 0) * k / 2 > most:
        group = 16
        while n_atoms * k / group * 18 > 2 * most:  # a cluster touches some 36 others
            group *= 2
    homes = _clusters(atoms, cell, r_cut, n_atoms, group).persist()
    sizes = homes.groupBy("lead").agg(F.sum("degree").alias("size")).orderBy("lead").toArrow()
    ids, size = sizes["lead"].to_numpy(), np.maximum(sizes["size"].to_numpy(), 1)
    pairs = _cluster_pairs(atoms.join(homes.select("atom_id", "lead"), "atom_id"), cell, r_cut, n_atoms).toArrow()
    src, dst = (np.searchsorted(ids, pairs[c].to_numpy()) for c in ("src", "dst"))
    w = pairs["w"].to_numpy().astype(float)
    shift = np.stack([pairs[c].to_numpy() for c in ("sx", "sy", "sz")], 1)
    a, b, v = [], [], []
    for t in range(k):
        one, two = src + t * len(ids), dst + boxes.tile_of(t, shift, tiles) * len(ids)
        a.append(np.minimum(one, two)[one != two])
        b.append(np.maximum(one, two)[one != two])
        v.append(w[one != two])
    n = len(ids) * k
    key, where = np.unique(np.concatenate(a) * n + np.concatenate(b), return_inverse=True)
    graph = (key // n, key % n, np.bincount(where, weights=np.concatenate(v), minlength=len(key)), np.tile(size, k))
    del pairs, src, dst, shift, a, b, v, key, where
    found = np.stack([multilevel(*graph, p, imbalance).reshape(k, len(ids)) for p in parts])
    each = len(parts) * k
    flat = found.reshape(each, len(ids)).T.astype(np.int32).ravel()
    ranks = pa.table({"lead": pa.array(ids, pa.int64()), "ranks": pa.ListArray.from_arrays(pa.array(np.arange(len(ids) + 1, dtype=np.int32) * each, pa.int32()), pa.array(flat))})
    return homes.join(atoms.sparkSession.createDataFrame(ranks), "lead").select("atom_id", "ranks")
