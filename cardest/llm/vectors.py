"""Embedding near-duplicates: int8 tile products with rigorous error bounds, full precision only where they leave doubt.

Equal vectors are one node with a count. Nodes are dealt to the nearest of a bounded set of pivot directions, a cell each.
Large cells are cut into blocks of bounded size, small ones bundled into one; two blocks meet unless for all their cells the
angle between the pivots, less the largest angles inside both cells, exceeds the angle of the threshold (triangle inequality,
so no link is lost). A pair of blocks is one task: it quantises
both, multiplies them tile by tile and returns one row per linked vector: how many links it has there and one edge of a
spanning forest, so that a group of n near copies costs n rows, not n squared.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from cardest.llm.common import attach, components, stored

#: Pivot directions: a bounded sample of the vectors, by hash of the identifier.
PIVOTS = 64
#: Vectors of one block, twice as many at most where cells are bundled; a task holds two blocks.
BLOCK_ROWS = 8192
#: Rows of one tile of the product.
TILE = 1024
#: Room for rounding in single and double precision.
SLACK = 1e-6


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Int8 codes, scales, norms of the decoded vectors and norms of the errors, of unit rows in double precision."""
    scale = np.abs(unit).max(axis=1) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    decoded = codes * scale[:, None]
    return codes, scale, np.linalg.norm(decoded, axis=1), np.linalg.norm(unit - decoded, axis=1)


def unit_rows(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def linked(x: np.ndarray, y: np.ndarray | None, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Index pairs of rows of ``x`` and ``y`` (or of ``x`` alone, each pair once) with cosine of at least ``threshold``.

    The product of codes is exact: it is done in single precision as long as sums of products fit its 24 bits. For unit
    vectors u, v with decoded u', v' and errors e, f: |u.v - u'.v'| <= |u'| |f| + |e|.
    """
    same = y is None
    cx, sx, nx, ex = quantise(x)
    cy, sy, _, ey = (cx, sx, nx, ex) if same else quantise(y)
    y = x if same else y
    kind = np.float32 if x.shape[1] * 127 * 127 < 2**24 else np.float64
    for j in range(0, len(y), TILE):
        right = cy[j : j + TILE].astype(kind).T
        most_s, most_e = sy[j : j + TILE].max(), ey[j : j + TILE].max()
        for i in range(0, (j + TILE) if same else len(x), TILE):
            product = cx[i : i + TILE].astype(kind) @ right
            # a bound per row first, then the pair's own, then the cosine itself
            rows = slice(i, i + TILE)
            floor = (threshold - SLACK - ex[rows] - nx[rows] * most_e) / (sx[rows] * most_s)
            a, b = np.nonzero(product >= floor.astype(kind)[:, None] - 1)
            p = product[a, b].astype(np.float64)
            a, b = a + i, b + j
            if same:
                keep = a < b
                a, b, p = a[keep], b[keep], p[keep]
            keep = p * sx[a] * sy[b] + nx[a] * ey[b] + ex[a] >= threshold - SLACK
            a, b = a[keep], b[keep]
            for at in range(0, len(a), 100_000):
                c, d = a[at : at + 100_000], b[at : at + 100_000]
                good = np.einsum("ij,ij->i", x[c], y[d]) >= threshold
                if good.any():
                    yield c[good], d[good]


def forest(a: np.ndarray, b: np.ndarray, n: int) -> np.ndarray:
    """Smallest index reachable from each of ``n`` nodes over the given pairs."""
    root = np.arange(n)
    while True:
        low = np.minimum(root[a], root[b])
        before = root.copy()
        np.minimum.at(root, a, low)
        np.minimum.at(root, b, low)
        np.minimum.at(root, before[a], low)
        np.minimum.at(root, before[b], low)
        root = root[root]
        if (root == before).all():
            return root


def near_vectors(table: DataFrame, threshold: float = 0.95, id_col: str = "vec_id", vector_col: str = "embedding", pivots: int = PIVOTS, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """Links of cosine ``threshold`` or more among all vectors.

    Returns ``vec_id, n_links, component_id, kept``, one row per input row. Vectors that are null, empty, zero or hold a
    null or non-finite component, and rows without identifier, link with nothing; vectors of different lengths never link.
    Equal vectors link with each other. Rows that repeat an identifier are one item with the links of all of them. Every
    pair with the wanted cosine is found (recall 1). An empty table gives an empty result; labels are not read.
    """
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    whole = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    rows = table.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).alias("vector"), F.coalesce(whole & F.col(id_col).isNotNull(), F.lit(False)).alias("ok"))
    good = rows.where("ok").select("vec_id", "vector")
    nodes = stored(good.groupBy("vector").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies")), "vector-nodes")
    pairs = _block_links(nodes, threshold, pivots, block_rows)
    found = components(pairs.select(F.col("node").alias("a"), F.col("root").alias("b")))
    links = pairs.groupBy("node").agg(F.sum("links").alias("links"))
    info = nodes.join(links, "node", "left").join(found, "node", "left")
    info = info.select("vector", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("root", "node").alias("component_id"))
    out = attach(good, "vector", "vec_id", info).select("vec_id", "n_links", "component_id")
    alone = rows.where("not ok").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def _block_links(nodes: DataFrame, threshold: float, pivots: int, block_rows: int) -> DataFrame:
    """``node, links, root``: per pair of blocks, the linked nodes with their number of links and smallest node reached."""
    sample = nodes.select("node", F.transform("vector", lambda x: x.cast("double")).alias("v")).orderBy(F.xxhash64("node"), "node").limit(pivots).toPandas()
    reach = math.acos(max(-1.0, min(1.0, threshold))) + SLACK
    by_width = {w: unit_rows(np.stack(g)) for w, g in sample["v"].groupby(sample["v"].map(len))}

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            width = b["vector"].map(len).to_numpy()
            cell, angle = np.zeros(len(b), dtype=np.int64), np.full(len(b), math.pi)
            for w in np.unique(width):
                here = np.flatnonzero(width == w)
                if w in by_width:
                    cosine = unit_rows(np.stack(b["vector"].iloc[here]).astype(np.float64)) @ by_width[w].T
                    cell[here] = cosine.argmax(axis=1)
                    angle[here] = np.arccos(np.clip(cosine.max(axis=1), -1, 1))
            yield pd.DataFrame({"width": width, "cell": cell, "angle": angle, "node": b["node"], "copies": b["copies"], "vector": b["vector"]})

    kind = nodes.schema["vector"].dataType.simpleString()  # vectors travel as they are stored
    placed = stored(nodes.mapInPandas(place, f"width int, cell int, angle double, node bigint, copies bigint, vector {kind}"), "vector-cells")
    cells = placed.groupBy("width", "cell").agg(F.max("angle").alias("angle"), F.count("*").alias("n"))
    small = F.when(F.col("n") < block_rows, F.col("n")).otherwise(0)
    before = F.sum(small).over(W.partitionBy("width").orderBy("cell")) - small  # at most ``pivots`` rows a width
    # a bundle is named by its number, a large cell by its own one, below zero
    bundle = F.when(F.col("n") < block_rows, F.floor(before / block_rows)).otherwise(-1 - F.col("cell")).cast("int")
    cells = stored(cells.withColumn("bundle", bundle), "vector-bundles")
    # a block's cells within reach: at most as many as there are pivots
    near_of = cells.select("width", F.col("cell").alias("other"), F.col("angle").alias("other_angle"))

    def meets(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            keep = []
            for w, c, o, r, s in zip(b["width"], b["cell"], b["other"], b["angle"], b["other_angle"], strict=True):
                p = by_width.get(w)
                keep.append(p is None or math.acos(float(np.clip(p[c] @ p[o], -1, 1))) <= r + s + reach + SLACK)
            yield b[keep][["width", "cell", "other"]]

    near = cells.select("width", "cell", "angle").join(near_of, "width").where("cell <= other").mapInPandas(meets, "width int, cell int, other int")
    blocks = F.when(F.col("bundle") < 0, F.ceil(F.col("n") / block_rows)).otherwise(1).cast("int")
    many = cells.select("width", "cell", "bundle", blocks.alias("blocks"))
    others = many.select("width", F.col("cell").alias("other"), F.col("bundle").alias("with"), F.col("blocks").alias("others"))
    meet = near.join(many, ["width", "cell"]).join(others, ["width", "other"])
    meet = meet.select("width", F.least("bundle", "with").alias("bundle"), F.greatest("bundle", "with").alias("with"), F.when(F.col("bundle") <= F.col("with"), F.col("blocks")).otherwise(F.col("others")).alias("blocks"), F.when(F.col("bundle") <= F.col("with"), F.col("others")).otherwise(F.col("blocks")).alias("others")).distinct()
    meet = meet.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).withColumn("j", F.explode(F.sequence(F.lit(0), F.col("others") - 1))).where("bundle < with or i <= j")
    meet = stored(meet.select(F.xxhash64("width", "bundle", "i", "with", "j").alias("pair"), "width", "bundle", "i", "with", "j"), "vector-meet")
    sides = meet.select("pair", "width", "bundle", F.col("i").alias("block"), F.lit(0).alias("side")).unionByName(
        meet.where("bundle <> with or i <> j").select("pair", "width", F.col("with").alias("bundle"), F.col("j").alias("block"), F.lit(1).alias("side"))
    )
    dealt = placed.join(many, ["width", "cell"]).withColumn("block", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    work = dealt.join(sides, ["width", "bundle", "block"]).select("pair", "side", "node", "copies", "vector")

    def link(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(["side", "node"], ignore_index=True)
        node, copies = group["node"].to_numpy(), group["copies"].to_numpy()
        cut = int((group["side"] == 0).sum())
        unit = unit_rows(np.stack(group["vector"]).astype(np.float64))
        shift = 0 if cut == len(group) else cut
        links, ends = np.zeros(len(group), dtype=np.int64), [(np.empty(0, np.int64),) * 2]
        for a, b in linked(unit[:cut], None if cut == len(group) else unit[cut:], threshold):
            b = b + shift
            np.add.at(links, a, copies[b])
            np.add.at(links, b, copies[a])
            root = forest(a, b, len(group))  # keep a forest of the batch only
            hit = np.flatnonzero(root != np.arange(len(group)))
            ends.append((hit, root[hit]))
        root = forest(*map(np.concatenate, zip(*ends, strict=True)), len(group))
        hit = np.flatnonzero(links)
        return pd.DataFrame({"node": node[hit], "links": links[hit], "root": node[root[hit]]})

    return stored(work.groupBy("pair").applyInPandas(link, "node bigint, links bigint, root bigint"), "vector-links")
