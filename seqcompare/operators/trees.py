"""Trees from matrices, and distances between trees: a tree is one task, trees of all functions, levels and trials go at once.

A tree is nested lists of leaf names with branch lengths in newick text. Ties go to the pair of smallest labels.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

Node = tuple  # (name or None, length, children)


def _square(pdf: pd.DataFrame) -> tuple[list[str], np.ndarray]:
    names = sorted({*pdf["i"], *pdf["j"]})
    at = {n: k for k, n in enumerate(names)}
    d = np.zeros((len(names), len(names)))
    i, j = pdf["i"].map(at).to_numpy(), pdf["j"].map(at).to_numpy()
    d[i, j] = d[j, i] = pdf["value"].to_numpy(float)
    return names, d


def _closest(d: np.ndarray, labels: list[str]) -> tuple[int, int]:
    upper = np.where(np.triu(np.ones(d.shape, bool), 1), d, np.inf)
    low = upper.min()
    i, j = np.nonzero(upper <= low + 1e-12 * max(1.0, abs(low)))
    best = min(range(len(i)), key=lambda k: tuple(sorted((labels[i[k]], labels[j[k]]))))
    return int(i[best]), int(j[best])


def upgma(names: list[str], d: np.ndarray) -> Node:
    nodes: list[Node] = [(n, 0.0, ()) for n in names]
    heights, sizes, labels, d = [0.0] * len(names), [1] * len(names), list(names), d.astype(float).copy()
    while len(nodes) > 1:
        i, j = _closest(d, labels)
        height = d[i, j] / 2
        parts = [(nodes[k][0], height - heights[k], nodes[k][2]) for k in (i, j)]
        row = (sizes[i] * d[i] + sizes[j] * d[j]) / (sizes[i] + sizes[j])
        d[i], d[:, i] = row, row
        d[i, i] = 0
        d = np.delete(np.delete(d, j, 0), j, 1)
        nodes[i], heights[i], sizes[i], labels[i] = (None, 0.0, tuple(parts)), height, sizes[i] + sizes[j], min(labels[i], labels[j])
        for held in (nodes, heights, sizes, labels):
            del held[j]
    return nodes[0]


def neighbor_joining(names: list[str], d: np.ndarray) -> Node:
    """An unrooted tree, given as one whose root has three children (or two, for two leaves)."""
    nodes: list[Node] = [(n, 0.0, ()) for n in names]
    labels, d = list(names), d.astype(float).copy()
    while len(nodes) > 3:
        n, total = len(nodes), d.sum(1)
        i, j = _closest((n - 2) * d - total[:, None] - total[None, :], labels)
        li = d[i, j] / 2 + (total[i] - total[j]) / (2 * (n - 2))
        parts = ((nodes[i][0], li, nodes[i][2]), (nodes[j][0], d[i, j] - li, nodes[j][2]))
        row = (d[i] + d[j] - d[i, j]) / 2
        d[i], d[:, i] = row, row
        d[i, i] = 0
        d = np.delete(np.delete(d, j, 0), j, 1)
        nodes[i], labels[i] = (None, 0.0, parts), min(labels[i], labels[j])
        del nodes[j], labels[j]
    if len(nodes) == 3:
        a, b, c = ((d[0, 1] + d[0, 2] - d[1, 2]) / 2, (d[0, 1] + d[1, 2] - d[0, 2]) / 2, (d[0, 2] + d[1, 2] - d[0, 1]) / 2)
        lengths = (a, b, c)
    else:
        lengths = (d[0, -1] / 2,) * len(nodes)
    return (None, 0.0, tuple((x[0], float(n), x[2]) for x, n in zip(nodes, lengths, strict=True))) if len(nodes) > 1 else nodes[0]


def newick(node: Node, top: bool = True) -> str:
    name, length, children = node
    own = f"({','.join(newick(c, False) for c in children)})" if children else _quoted(name)
    return own + (";" if top else f":{length:.6g}")


def _quoted(name: str) -> str:
    return name if re.fullmatch(r"[\w./-]+", name) else "'" + name.replace("'", "''") + "'"


def parse(text: str) -> Node:
    tokens = re.findall(r"'(?:[^']|'')*'|[(),:;]|[^(),:;\s']+", text)
    at = 0

    def node() -> Node:
        nonlocal at
        children: list[Node] = []
        name = None
        if tokens[at] == "(":
            while tokens[at] in "(,":
                at += 1
                children.append(node())
            at += 1
        if at < len(tokens) and tokens[at] not in ",):;":
            name = tokens[at][1:-1].replace("''", "'") if tokens[at][0] == "'" else tokens[at]
            at += 1
        length = 0.0
        if at < len(tokens) and tokens[at] == ":":
            length, at = float(tokens[at + 1]), at + 2
        return (name if not children else None, length, tuple(children))

    return node()


def leaves(node: Node) -> frozenset[str]:
    return frozenset([node[0]]) if not node[2] else frozenset().union(*(leaves(c) for c in node[2]))


def clades(node: Node) -> set[frozenset[str]]:
    """Leaf sets of the inner nodes, the root's among them."""
    if not node[2]:
        return set()
    return {leaves(node)}.union(*(clades(c) for c in node[2]))


def root(node: Node, mode: str = "midpoint", outgroup: str | None = None) -> Node:
    """A rooted form: at the middle of the longest path between leaves, or at an outgroup's branch."""
    edges: dict[int, list[tuple[int, float]]] = {}
    names: dict[int, str] = {}
    count = 0

    def walk(n: Node) -> int:
        nonlocal count
        me, count = count, count + 1
        edges.setdefault(me, [])
        if not n[2]:
            names[me] = n[0]
        for c in n[2]:
            kid = walk(c)
            edges[me].append((kid, c[1]))
            edges[kid].append((me, c[1]))
        return me

    walk(node)

    def far(start: int) -> tuple[dict[int, float], dict[int, int]]:
        dist, before, queue = {start: 0.0}, {start: -1}, [start]
        for x in queue:
            for y, n in edges[x]:
                if y not in dist:
                    dist[y], before[y] = dist[x] + n, x
                    queue.append(y)
        return dist, before

    def build(at: int, above: int, length: float) -> Node:
        kids = tuple(build(y, at, n) for y, n in edges[at] if y != above)
        if len(kids) == 1 and at not in names:
            return (kids[0][0], kids[0][1] + length, kids[0][2])
        return (names.get(at), length, kids)

    if len(names) < 2:
        return node
    if mode == "outgroup":
        leaf = next(k for k, n in names.items() if n == outgroup)
        other, n = edges[leaf][0]
        return (None, 0.0, (build(leaf, other, n / 2), build(other, leaf, n / 2)))
    first = min(names, key=lambda k: names[k])
    dist, _ = far(first)
    a = max(sorted(names, key=lambda k: names[k]), key=lambda k: dist[k])
    dist, before = far(a)
    b = max(sorted(names, key=lambda k: names[k]), key=lambda k: dist[k])
    half, x = dist[b] / 2, b
    while before[x] != -1 and dist[before[x]] > half:
        x = before[x]
    up = before[x]
    return (None, 0.0, (build(x, up, dist[x] - half), build(up, x, half - dist[up])))


def robinson_foulds(a: Node, b: Node, rooted: bool = True) -> int:
    """Clades in one tree only; without a root, splits in one only."""
    if rooted:
        return len(clades(a) ^ clades(b))
    every = leaves(a)
    least = min(every)

    def splits(n: Node) -> set[frozenset[str]]:
        out = {c if least not in c else every - c for c in clades(n)}
        return {c for c in out if 1 < len(c) < len(every) - 1}

    return len(splits(a) ^ splits(b))


def matching_cluster(a: Node, b: Node) -> int:
    """Least total of symmetric differences over perfect matchings of clusters, the smaller set padded by empty ones."""
    x, y = sorted(clades(a), key=sorted), sorted(clades(b), key=sorted)
    common = set(x) & set(y)  # a cluster of both trees can be matched with itself at no loss
    x, y = [c for c in x if c not in common], [c for c in y if c not in common]
    n = max(len(x), len(y))
    cost = np.zeros((n, n))
    for i in range(n):
        for j in range(n):
            cost[i, j] = len((x[i] if i < len(x) else frozenset()) ^ (y[j] if j < len(y) else frozenset()))
    return int(round(sum(cost[i, j] for i, j in enumerate(assignment(cost)))))


def assignment(cost: np.ndarray) -> list[int]:
    """The column of each row in a least-cost assignment, by shortest augmenting paths with potentials."""
    n = len(cost)
    u, v, match = np.zeros(n + 1), np.zeros(n + 1), np.zeros(n + 1, int)
    for i in range(1, n + 1):
        match[0], j0 = i, 0
        low, used, way = np.full(n + 1, np.inf), np.zeros(n + 1, bool), np.zeros(n + 1, int)
        while True:
            used[j0] = True
            i0 = match[j0]
            free = ~used[1:]
            now = cost[i0 - 1] - u[i0] - v[1:]
            better = free & (now < low[1:])
            low[1:][better] = now[better]
            way[1:][better] = j0
            j1 = int(np.argmin(np.where(free, low[1:], np.inf))) + 1
            delta = low[j1]
            u[match[used]] += delta
            v[used] -= delta
            low[~used] -= delta
            j0 = j1
            if match[j0] == 0:
                break
        while j0:
            match[j0], j0 = match[way[j0]], way[j0]
    out = [0] * n
    for j in range(1, n + 1):
        out[match[j] - 1] = j - 1
    return out


BUILDERS = {"upgma": upgma, "nj": neighbor_joining}


def build(matrices: DataFrame, keys: list[str], builders: tuple[str, ...] = ("upgma", "nj")) -> DataFrame:
    """(keys, builder, newick) for each group of keys of a distance matrix without nulls."""
    kinds = {f.name: f.dataType.simpleString() for f in matrices.schema}

    def work(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        names, d = _square(pdf)
        return pd.DataFrame([(*key, b, newick(BUILDERS[b](names, d))) for b in builders], columns=[*keys, "builder", "newick"])

    schema = ", ".join(f"`{k}` {kinds[k]}" for k in keys) + ", builder string, newick string"
    return matrices.groupBy(*keys).applyInPandas(work, schema)


def scores(trees: DataFrame, gold: str, metrics: tuple[str, ...] = ("rf", "mc")) -> DataFrame:
    """Each tree's distance from a gold tree given in newick. Trees of neighbor joining are rooted at their middle for clusters."""
    kept = [c for c in trees.columns if c != "newick"]
    kinds = {f.name: f.dataType.simpleString() for f in trees.schema}

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        best = parse(gold)
        for pdf in frames:
            rows = []
            for record in pdf.to_dict("records"):
                tree = parse(record["newick"])
                tree = root(tree) if record["builder"] == "nj" else tree
                for m in metrics:
                    value = robinson_foulds(tree, best, rooted=record["builder"] != "nj") if m == "rf" else matching_cluster(tree, best)
                    rows.append((*(record[c] for c in kept), m, float(value)))
            yield pd.DataFrame(rows, columns=[*kept, "metric", "score"])

    return trees.mapInPandas(work, ", ".join(f"`{c}` {kinds[c]}" for c in kept) + ", metric string, score double")


def heights(tree: Node) -> list[tuple[str, float]]:
    """Inner nodes of an ultrametric tree: their leaves joined by commas, and their height."""
    out: list[tuple[str, float]] = []

    def walk(n: Node) -> float:
        if not n[2]:
            return 0.0
        h = max(walk(c) + c[1] for c in n[2])
        out.append((",".join(sorted(leaves(n))), h))
        return h

    walk(tree)
    return out


def impute(mat: DataFrame, factor: float = 1.0) -> DataFrame:
    """Missing distances as the largest of their matrix times ``factor``, marked in ``imputed``."""
    top = F.max("value").over(Window.partitionBy("fn"))
    return mat.select("*", F.col("value").isNull().alias("imputed")).withColumn("value", F.coalesce("value", top * factor))


def from_taxonomy(rows: list[tuple[str, ...]]) -> Node:
    """A tree from paths: (group, ..., leaf). Groups of many children stay as they are."""
    def make(paths: list[tuple[str, ...]]) -> tuple[Node, ...]:
        by: dict[str, list[tuple[str, ...]]] = {}
        for p in sorted(paths):
            by.setdefault(p[0], []).append(p[1:])
        return tuple((k, 1.0, ()) if not rest[0] else (None, 1.0, make(rest)) for k, rest in by.items())

    return (None, 0.0, make(rows))
