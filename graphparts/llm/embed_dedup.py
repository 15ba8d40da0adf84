"""Near duplicates among embeddings by int8 tile products with rigorous error bounds.

Every unit vector x is stored as ``scale * q`` with int8 components q, and the length of
what that leaves out, ``e = |x - scale * q|``, is kept with it. A tile product of the int8
parts (exact integers) then gives every cosine of two tiles within
``e_x + e_y + 3 e_x e_y``, by the Cauchy-Schwarz inequality. Only pairs whose upper bound
reaches the threshold are computed again from the given components in double precision,
and that value alone decides, so no link is lost and none is false.

Equal vectors are one class and compared once. A vector is quantised once, and only its int8 form is sent
to the pairs of tiles it belongs to, all of which are visited. Each returns the vectors that have a possible
partner there, never a row for each pair; the given components of these alone are sent to be computed again,
and a pair of tiles then returns a spanning forest and the links of its members.

Defined results: vectors that are null, empty or zero or hold null or non-finite components, and rows
with a null id, link with nothing; vectors of different lengths do not link; repeated rows
are copies; an empty table gives an empty table. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import mapped, written
from graphparts.llm.ngram_join import _in_groups, _sides, _tiled
from graphparts.operators.components import connected_components


def quantised(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 components, scales, and the lengths of the remainders of the rows of ``unit``."""
    scale = np.abs(unit).max(axis=1) / 127
    q = np.rint(unit / scale[:, None])
    left_out = np.linalg.norm(unit - q * scale[:, None], axis=1)
    return q.astype(np.int8), scale, left_out


#: Room for the rounding of the double-precision steps of the bound itself.
_SLACK = 1e-9


def possible_pairs(left: tuple, right: tuple, threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Row numbers of the pairs whose cosine may reach ``threshold``."""
    (qa, sa, ea), (qb, sb, eb) = left, right
    exact = np.float32 if 127 * 127 * qa.shape[1] < 2**24 else np.float64
    products = qa.astype(exact) @ qb.astype(exact).T
    worst = eb.max()
    least = (threshold - _SLACK - ea - worst - 3 * ea * worst) / sa
    i, j = np.nonzero(products * sb.astype(exact) >= (least * (1 - 1e-6)).astype(exact)[:, None])
    # The products are whole numbers held exactly, so each pair's own bound needs no second product.
    keep = products[i, j].astype(float) * sa[i] * sb[j] + ea[i] + eb[j] + 3 * ea[i] * eb[j] >= threshold - _SLACK
    return i[keep], j[keep]


def cosines(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a * b).sum(axis=1) / (np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1)))


def _unit(x: np.ndarray) -> np.ndarray:
    # Dividing by the largest component first keeps squares finite.
    unit = x / np.abs(x).max(axis=1)[:, None]
    unit /= np.linalg.norm(unit, axis=1)[:, None]
    return unit


def _components(lists: pa.Array, n: int) -> np.ndarray:
    return lists.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(n, -1)


def _coded(batch: pa.RecordBatch) -> dict:
    """The int8 components as bytes, the scale and the remainder of every vector."""
    dims, code, scale, rest = batch.column("dim").to_numpy(), [b""] * batch.num_rows, np.zeros(batch.num_rows), np.zeros(batch.num_rows)
    for dim in np.unique(dims):
        at = np.flatnonzero(dims == dim)
        q, scale[at], rest[at] = quantised(_unit(_components(batch.column("embedding").take(pa.array(at)), len(at))))
        for k, row in zip(at.tolist(), q, strict=True):
            code[k] = row.tobytes()
    return {k: batch.column(k) for k in ("d1", "d2", "dim")} | {"code": code, "scale": scale, "rest": rest}


#: Rows of a tile compared at once, which bounds the pairs held at once.
_STRIP = 256


def _strips(left: np.ndarray, right: np.ndarray, same: bool, coded: tuple, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Possible pairs of a pair of tiles, each once, some rows of the left tile at a time."""
    for begin in range(0, len(left), _STRIP):
        part = left[begin : begin + _STRIP]
        other = right[right >= begin] if same else right
        i, j = possible_pairs(tuple(c[part] for c in coded), tuple(c[other] for c in coded), threshold)
        a, b = part[i], other[j]
        yield (a[a < b], b[a < b]) if same else (a, b)


def _tile_candidates(threshold: float):
    """Vectors of a pair of tiles that some vector of the other one may be linked with: a row a vector, whatever the pairs."""

    def run(group: pa.Table) -> list[dict]:
        left, right, same = _sides(group)
        if len(left) == 0 or len(right) == 0 or (same and len(left) < 2):
            return []
        q = np.frombuffer(b"".join(group.column("code").to_pylist()), np.int8).reshape(group.num_rows, -1)
        met = np.zeros(group.num_rows, bool)
        for a, b in _strips(left, right, same, (q, group.column("scale").to_numpy(), group.column("rest").to_numpy()), threshold):
            met[a] = met[b] = True
        return group.select(["dim", "_a", "_b", "_own", "d1", "d2"]).filter(pa.array(met)).to_pylist() if met.any() else []

    return run


def _joining(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Of the pairs those that join groups not yet joined; ``label``, the least place in each one's group, follows."""
    out: list[tuple[int, int]] = []
    while True:
        apart = label[a] != label[b]
        a, b = a[apart], b[apart]
        if len(a) == 0:
            return out
        high, low = np.maximum(label[a], label[b]), np.minimum(label[a], label[b])
        roots, first = np.unique(high, return_index=True)
        parent = np.arange(len(label))
        parent[roots] = low[first]
        while (parent[parent] != parent).any():
            parent = parent[parent]
        label[:] = parent[label]
        out += zip(a[first].tolist(), b[first].tolist(), strict=True)


def _tile_links(threshold: float):
    def run(group: pa.Table) -> list[dict]:
        left, right, same = _sides(group)
        if len(left) == 0 or len(right) == 0 or (same and len(left) < 2):
            return []
        v, copies = group.column("rep").to_numpy(), group.column("copies").to_numpy()
        x = _components(group.column("embedding").combine_chunks(), len(v))
        links, label, forest = np.zeros(len(v)), np.arange(len(v)), []
        for a, b in _strips(left, right, same, quantised(_unit(x)), threshold):
            for at in range(0, len(a), 100_000):
                c, d = a[at : at + 100_000], b[at : at + 100_000]
                linked = cosines(x[c], x[d]) >= threshold
                c, d = c[linked], d[linked]
                links += np.bincount(c, copies[d], len(v)) + np.bincount(d, copies[c], len(v))
                forest += _joining(label, c, d)
        out = [{"src": int(v[i]), "dst": int(v[j]), "links": 0} for i, j in forest]
        return out + [{"src": int(v[k]), "dst": None, "links": int(links[k])} for k in np.flatnonzero(links)]

    return run


#: Components of a tile's vectors, so that long vectors have smaller tiles.
_TILE_COMPONENTS = 1 << 22


def near_duplicate_vectors(df: DataFrame, *, vec_id: str = "vec_id", embedding: str = "embedding", threshold: float = 0.95, tile: int = 8192) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` for every row of ``df``."""
    e = F.col("embedding")
    sound = F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(e, lambda x: x != 0) & F.col("vec_id").isNotNull()
    plain = df.select(F.col(vec_id).cast("bigint").alias("vec_id"), F.col(embedding).alias("embedding"))
    keyed = plain.withColumn("sound", F.coalesce(sound, F.lit(False)))
    mark = lambda c: F.when(F.col("sound"), c)
    keyed = keyed.select("vec_id", "embedding", mark(F.xxhash64("embedding")).alias("d1"), mark(F.xxhash64(F.lit(1), "embedding")).alias("d2"))
    reps = written(
        keyed.where("d1 is not null").groupBy("d1", "d2").agg(F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.min_by("embedding", "vec_id").alias("embedding")).withColumn("dim", F.size("embedding")),
        "vectors",
    )
    # One row a length of vectors, so no more than the longest vector has components.
    sizes = reps.groupBy("dim").agg(F.count("*").alias("c"))
    codes = written(mapped(reps.select("d1", "d2", "dim", "embedding"), _coded, "d1 bigint, d2 bigint, dim int, code binary, scale double, rest double"), "codes")
    rows = F.least(F.lit(tile), F.greatest(F.lit(512), F.floor(_TILE_COMPONENTS / F.col("dim")).cast("int")))
    tiles = _tiled(codes.join(F.broadcast(sizes), "dim"), "dim", "d1", "c", rows)
    met = written(_in_groups(tiles, "dim", _tile_candidates(threshold), "dim int, _a int, _b int, _own int, d1 bigint, d2 bigint"), "met")
    again = met.join(reps.select("d1", "d2", "rep", "copies", "embedding"), ["d1", "d2"])
    found = written(_in_groups(again, "dim", _tile_links(threshold), "src bigint, dst bigint, links bigint"), "links")
    components = connected_components(found.where("dst is not null")).withColumnsRenamed({"v": "rep", "component": "component_id"})
    links = found.where("dst is null").groupBy(F.col("src").alias("rep")).agg(F.sum("links").alias("links"))
    about = reps.select("d1", "d2", "rep", "copies").join(components, "rep", "left").join(links, "rep", "left")
    component = F.coalesce("component_id", "rep", "vec_id")
    return (
        keyed.select("vec_id", "d1", "d2")
        .join(about, ["d1", "d2"], "left")
        .select(
            "vec_id",
            (F.coalesce("links", F.lit(0)) + F.coalesce("copies", F.lit(1)) - 1).cast("bigint").alias("n_links"),
            component.alias("component_id"),
            F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"),
        )
    )
