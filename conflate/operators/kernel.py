"""Tile kernel: pairs, local TF-IDF and edit scores of a tile in one vectorised function.

Places are shuffled once, with their halo, instead of shuffling every (centroid, neighbour, term) row.  Tiles are
bounded by the density of places times the tile's area; dense tiles should be made smaller (``side``), down to
a few radii.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from conflate.functions.geo import EARTH_M
from conflate.functions.similarity import clean, edit_similarity, token_sort
from conflate.operators.candidates import tiles

OUT = "c string, m string, dist_m double, name_c string, name_m string, s_addr double, addr_missing boolean"


def _ranges(lengths: np.ndarray) -> np.ndarray:
    """0..l-1 for each length l, one after the other."""
    ends = np.cumsum(lengths)
    return np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - lengths, lengths)


def _neighbours(lat: np.ndarray, lon: np.ndarray, src: np.ndarray, core: np.ndarray, r: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(c, m, metres) of the tile's ordered cross-source pairs with the centroid in the core."""
    order = np.argsort(lat, kind="stable")
    s, mid = lat[order], np.flatnonzero(core)
    up = np.degrees(r * (1 + 1e-9) / EARTH_M)
    lo, hi = np.searchsorted(s, lat[mid] - up, "left"), np.searchsorted(s, lat[mid] + up, "right")
    c = np.repeat(mid, hi - lo)
    m = order[np.repeat(lo, hi - lo) + _ranges(hi - lo)]
    cross = src[m] != src[c]
    c, m = c[cross], m[cross]
    p, q = np.radians(lat[c]), np.radians(lat[m])
    a = np.sin((q - p) / 2) ** 2 + np.cos(p) * np.cos(q) * np.sin(np.radians(lon[m] - lon[c]) / 2) ** 2
    d = 2 * EARTH_M * np.arcsin(np.sqrt(np.minimum(a, 1.0)))
    ok = d <= r
    return c[ok], m[ok], d[ok]


def _frequencies(terms: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """First entry of each place (and the end), term number and term frequency of the places' distinct terms."""
    col = terms.combine_chunks()
    n = np.asarray(pc.fill_null(pc.list_value_length(col), 0))
    place = np.repeat(np.arange(len(n)), n)
    codes = np.asarray(pc.dictionary_encode(pc.list_flatten(col)).indices) if len(place) else np.zeros(0, np.int64)
    width = int(codes.max()) + 1 if len(codes) else 1
    key, count = np.unique(place * width + codes, return_counts=True)
    return np.searchsorted(key // width, np.arange(len(n) + 1)), key % width, count / n[key // width]


def _cosines(c: np.ndarray, m: np.ndarray, first: np.ndarray, term: np.ndarray, tf: np.ndarray) -> np.ndarray:
    """Cosine of centroid and neighbour, weighted by the terms' rarity among the centroid and its neighbours."""
    mid = np.unique(c)
    row, col = np.concatenate([c, mid]), np.concatenate([m, mid])
    size = first[col + 1] - first[col]
    pair = np.repeat(np.arange(len(row)), size)
    entry = np.repeat(first[col], size) + _ranges(size)
    width = int(term.max()) + 1 if len(term) else 1
    key, at, df = np.unique(row[pair] * width + term[entry], return_inverse=True, return_counts=True)
    corpus = np.bincount(row[size > 0], minlength=int(row.max()) + 1 if len(row) else 1)
    weight = tf[entry] * np.log(corpus[row[pair]] / df[at])
    own = np.zeros(len(key))
    mine = pair >= len(c)
    own[at[mine]] = weight[mine]
    dot, square = np.bincount(pair, weight * own[at], len(row)), np.bincount(pair, weight * weight, len(row))
    norm = np.sqrt(square[: len(c)]) * np.sqrt(square[len(c) + np.searchsorted(mid, c)])
    return np.divide(dot[: len(c)], norm, out=np.zeros(len(c)), where=norm > 0)


def _score(table: pa.Table, r: float) -> pa.Table:
    src = np.asarray(pc.dictionary_encode(table.column("src").combine_chunks()).indices)
    c, m, d = _neighbours(table.column("lat").to_numpy(), table.column("lon").to_numpy(), src, table.column("core").to_numpy(), r)
    addr = _cosines(c, m, *_frequencies(table.column("terms")))
    ci, mi = pa.array(c), pa.array(m)
    uid, name = table.column("uid"), table.column("tname")
    gone = np.asarray(table.column("taddr").is_null())
    cols = [uid.take(ci), uid.take(mi), pa.array(d), name.take(ci), name.take(mi), pa.array(np.round(addr, 6)), pa.array(gone[c] | gone[m])]
    return pa.table(dict(zip([x.split()[0] for x in OUT.split(", ")], cols)))


def score_tiles(places: DataFrame, side: float = 1000.0, r: float = 100.0) -> DataFrame:
    """The rows of ``features.build(..., 'hybrid')`` for all pairs within r.

    The kernel gives pairs and address scores; the edit distance of the names is a projection after it.
    """
    p = places.select("uid", "src", "lat", "lon", token_sort(F.col("name")).alias("tname"), token_sort(F.col("address")).alias("taddr"), F.filter(F.split(clean(F.col("address")), " "), lambda t: t != "").alias("terms"))

    def run(table: pa.Table) -> pa.Table:
        return _score(table, r)

    got = tiles(p, side, r).groupBy("ty", "tx").applyInArrow(run, OUT)
    missing = F.col("name_c").isNull() | F.col("name_m").isNull()
    return got.select("c", "m", "dist_m", F.when(missing, F.lit(0.0)).otherwise(F.round(edit_similarity(F.col("name_c"), F.col("name_m")), 6)).alias("s_name"), "s_addr", missing.alias("name_missing"), "addr_missing")
