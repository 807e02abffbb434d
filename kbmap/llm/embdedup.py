"""Embedding near-duplicates by product quantisation.

Equal vectors collapse first. A coarse k-means, fitted on a bounded sample, cuts the distinct vectors
into inverted lists; sub-space codebooks code the residuals. Each vector probes every list that can hold a vector within the
threshold, by bounds and not by a count: look-up tables give the asymmetric angle to every coded member, members whose angle can reach the
threshold (the angle between a member and its code is known, so the triangle inequality loses none of a probed list)
are compared by exact double-precision cosine. Large lists are cut, small neighbours share a bundle of bounded size, so a vector is
sent once for many lists and no task holds a large list; a bundle emits per vector a count and a spanning link, never its pairs.

Vectors that are null, empty, zero, or hold null or non-finite components link with nothing; vectors of different widths don't link.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Cut, connected_components


@dataclass(frozen=True)
class Settings:
    threshold: float = 0.9
    sample_rows: int = 20_000  # most rows that fit the quantisers
    list_size: int = 400  # rows a list holds on average
    max_lists: int = 4096
    subspaces: int = 8
    codes: int = 64
    block: int = 2048  # members that a cut of a large list holds on average
    bundle: int = 16384  # most members of neighbouring lists that one task holds, and vectors of a slice that it compares with them
    held_values: int = 1 << 20  # components that a bundle holds at most, for wide vectors
    seed: int = 5


def _kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> np.ndarray:
    k = min(k, len(x))
    c = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = np.empty(len(x), np.int64)
        for a in range(0, len(x), 4096):
            near[a : a + 4096] = ((c * c).sum(1) - 2 * x[a : a + 4096] @ c.T).argmin(1)
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        n = np.bincount(near, minlength=k)
        c[n > 0] = total[n > 0] / n[n > 0, None]
    return c


class Quantiser:
    """Coarse centres and residual codebooks."""

    def __init__(self, x: np.ndarray, n_lists: int, s: Settings):
        rng = np.random.default_rng(s.seed)
        self.centres = _kmeans(x, n_lists, rng)
        self.cuts = np.array_split(np.arange(x.shape[1]), min(s.subspaces, x.shape[1]))
        r = x - self.centres[self.near(x, 1)[:, 0]]
        self.books = [_kmeans(r[:, c], s.codes, rng) for c in self.cuts]

    def near(self, x: np.ndarray, probes: int) -> np.ndarray:
        """The nearest lists of each row, nearest first."""
        d = (self.centres * self.centres).sum(1) - 2 * x @ self.centres.T
        probes = min(probes, d.shape[1])
        top = np.argpartition(d, probes - 1, axis=1)[:, :probes]
        return np.take_along_axis(top, np.take_along_axis(d, top, 1).argsort(1, kind="stable"), 1)

    def reachable(self, x: np.ndarray, own: np.ndarray, threshold: float, radius: np.ndarray) -> np.ndarray:
        """Mask (row, list) of the lists that may hold a unit vector whose cosine with a row is the threshold or more; ``own`` is the row's nearest centre.

        A member lies within its list's radius of the centre (negative for empty lists), and on its centre's side of the
        plane half-way to the row's own centre: across that plane's normal the best unit vector in the row's cone must get there.
        """
        reach, norms = float(np.sqrt(max(0.0, 2 - 2 * threshold))), (self.centres * self.centres).sum(1)
        dots, c = x @ self.centres.T, self.centres[own]
        d = np.maximum((x * x).sum(1)[:, None] + norms - 2 * dots, 0)
        apart = np.sqrt(np.maximum(norms[own][:, None] + norms - 2 * c @ self.centres.T, 0))
        along = dots - dots[np.arange(len(x)), own][:, None]
        best = threshold * along + np.sqrt(max(0.0, 1 - threshold**2)) * np.sqrt(np.maximum(apart**2 - along**2, 0))
        best = np.where(along >= threshold * apart, apart, best)
        return (radius >= 0) & (np.sqrt(d) <= reach + radius + 1e-6) & (best >= (norms - norms[own][:, None]) / 2 - 1e-6)

    def code(self, x: np.ndarray, lists: np.ndarray) -> np.ndarray:
        """Codes of the residuals."""
        r = x - self.centres[lists]
        return np.stack([((b * b).sum(1) - 2 * r[:, c] @ b.T).argmin(1).astype(np.uint8) for c, b in zip(self.cuts, self.books)], 1)

    def back(self, codes: np.ndarray, lists: np.ndarray) -> np.ndarray:
        """What codes stand for."""
        out = self.centres[lists].copy()
        for k, (c, book) in enumerate(zip(self.cuts, self.books)):
            out[:, c] += book[codes[:, k]]
        return out

    def tables(self, q: np.ndarray) -> list[np.ndarray]:
        """Look-up tables (code, query) of products; single precision, as exact cosines follow."""
        return [(book @ q[:, c].T).astype(np.float32) for c, book in zip(self.cuts, self.books)]

    @staticmethod
    def products(tables: list[np.ndarray], codes: np.ndarray) -> np.ndarray:
        """(member, query): products of queries with the coded residuals, summed from look-up tables a row at a time."""
        total = tables[0][codes[:, 0]]
        for k in range(1, len(tables)):
            total += tables[k][codes[:, k]]
        return total


def _spanning(n: int, edges: np.ndarray) -> np.ndarray:
    """The smallest vertex that each of n vertices reaches by the (m, 2) edges."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[edges[:, 0]], label[edges[:, 1]])
        new = label.copy()
        np.minimum.at(new, edges[:, 0], low)
        np.minimum.at(new, edges[:, 1], low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def distinct_vectors(embeddings: DataFrame) -> DataFrame:
    """(vec_id, embedding, rep): rep is the smallest vec_id of equal vectors, null for vectors that link with nothing."""
    v = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    usable = (
        F.col("embedding").isNotNull()
        & (F.size("embedding") > 0)
        & F.forall("embedding", lambda x: F.coalesce(~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))), F.lit(False)))
        & F.exists("embedding", lambda x: x != 0)
    )
    return v.withColumn("ok", F.coalesce(usable, F.lit(False)) & F.col("vec_id").isNotNull())


_FOUND = "rep long, links long, other long"


def _bundles(sizes: dict[int, int], centres: np.ndarray, s: Settings, most: int) -> tuple[list[tuple[int, int, int]], int]:
    """(list, first bundle, bundles) and the number of bundles: large lists are cut into bundles of their own, small neighbours share one of ``most`` members."""
    order = np.argsort(centres @ np.linalg.svd(centres, full_matrices=False)[2][0], kind="stable") if len(centres) > 1 else [0]
    out, n, room = [], 0, 0
    for x in map(int, order):
        size = sizes.get(x, 0)
        if size > most:
            cuts = -(-size // s.block)
            out.append((x, n, cuts))
            n, room = n + cuts, 0
        elif size:
            if size > room:
                n, room = n + 1, most
            room -= size
            out.append((x, n - 1, 1))
    return out, n


def _links(cut: Cut, reps: DataFrame, width: int, n: int, s: Settings) -> DataFrame:
    """(rep, links, other) of distinct vectors of one width: counts of linked rows, and links that span what hangs together."""
    spark = reps.sparkSession
    part = min(1.0, 1.2 * s.sample_rows / n)
    train = reps.select("embedding").where(F.abs(F.xxhash64("rep")) % 1_000_000 < F.lit(int(part * 1_000_000))).limit(s.sample_rows)
    sample = np.array([r[0] for r in train.collect()] or [reps.first().embedding], dtype=float)
    sample /= np.linalg.norm(sample, axis=1, keepdims=True)
    model = spark.sparkContext.broadcast(Quantiser(sample, max(1, min(s.max_lists, n // s.list_size)), s))  # bounded by max_lists

    def assign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = model.value
        for b in batches:
            if not b.num_rows:
                continue
            flat = b.column(2).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
            unit = flat / np.linalg.norm(flat, axis=1, keepdims=True)
            own = np.concatenate([q.near(unit[a : a + 1024], 1)[:, 0] for a in range(0, len(unit), 1024)])
            codes = q.code(unit, own)
            away = np.sqrt(((unit - q.centres[own]) ** 2).sum(1))
            yield pa.RecordBatch.from_arrays(
                [b.column(0), b.column(1), pa.array(list(unit), pa.list_(pa.float64())), pa.array(own, pa.int64()), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(away)],
                ["rep", "copies", "unit", "list", "code", "away"],
            )

    coded = cut(reps.select("rep", "copies", "embedding").mapInArrow(assign, "rep long, copies long, unit array<double>, list long, code binary, away double"))
    sizes = coded.groupBy("list").agg(F.count(F.lit(1)), F.max("away")).collect()  # one row per list, at most max_lists
    most = max(s.block, min(s.bundle, s.held_values // width))
    placed, n_bundles = _bundles({int(r[0]): int(r[1]) for r in sizes}, model.value.centres, s, most)
    places = spark.createDataFrame(placed, "list long, first long, cuts long")
    first, cuts = (np.zeros(len(model.value.centres), np.int64) for _ in range(2))
    for x, f, c in placed:
        first[x], cuts[x] = f, c
    radius = np.full(len(model.value.centres), -1.0)
    for r in sizes:
        radius[r[0]] = r[2]

    def probe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = model.value
        for whole in batches:
            for b in (whole.slice(k, 512) for k in range(0, whole.num_rows, 512)):
                unit = b.column(1).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)
                mask = q.reachable(unit, b.column(2).to_numpy(zero_copy_only=False), s.threshold, radius)
                spans = []
                for lists in map(np.flatnonzero, mask):
                    n_cuts = cuts[lists]
                    starts = np.repeat(first[lists] - n_cuts.cumsum() + n_cuts, n_cuts)
                    spans.append(np.unique(starts + np.arange(len(starts))))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(spans, pa.list_(pa.int64()))], ["rep", "unit", "list", "bundles"])

    probed = coded.select("rep", "unit", "list").mapInArrow(probe, "rep long, unit array<double>, list long, bundles array<long>")
    held = coded.join(F.broadcast(places), "list").withColumn("bundle", F.col("first") + F.pmod(F.xxhash64("rep"), F.col("cuts")))
    # A vector goes once to each bundle that holds lists it probes. Those of a bundle are dealt over slices, so that one which many probe is not one task.
    asked = probed.select("rep", "unit", "list", F.explode("bundles").alias("bundle"))
    deal = -(-n // most)
    held = held.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(deal - 1))))
    asked = asked.withColumn("slice", F.pmod(F.xxhash64("rep", F.lit(1)), F.lit(deal)).cast("int"))

    def compare(key, left, right):
        q = model.value
        empty = pd.DataFrame({"rep": pd.Series(dtype="int64"), "links": pd.Series(dtype="int64"), "other": pd.Series(dtype="int64")})
        if not len(left) or not len(right):
            return empty
        left = left.sort_values(["list", "rep"], kind="stable")
        m_id, m_n, m_x, m_list = left["rep"].to_numpy(), left["copies"].to_numpy(), np.stack(left["unit"].to_numpy()), left["list"].to_numpy()
        codes = np.frombuffer(b"".join(left["code"]), np.uint8).reshape(len(left), -1)
        # The angle between a query and a member is no smaller than the query's angle to the code less the member's own.
        back = q.back(codes, m_list)
        length = np.sqrt((back * back).sum(1))
        own_angle = np.arccos(np.clip((back * m_x).sum(1) / np.maximum(length, 1e-300), -1, 1))
        least = length * np.cos(np.minimum(np.pi, np.arccos(s.threshold) + own_angle)) - 1e-5
        edges_of = [0, *(np.flatnonzero(np.diff(m_list)) + 1).tolist(), len(m_list)]
        q_id, q_x, q_list = right["q_rep"].to_numpy(), np.stack(right["q_unit"].to_numpy()), right["q_list"].to_numpy()
        ids = np.unique(np.concatenate([m_id, q_id]))
        count, edges = np.zeros(len(q_id), np.int64), []
        for a in range(0, len(q_id), 1024):
            x = q_x[a : a + 1024]
            mask, tables, to_centres = q.reachable(x, q_list[a : a + 1024], s.threshold, radius), q.tables(x), x @ q.centres.T
            for lo, hi in zip(edges_of, edges_of[1:]):
                who = np.flatnonzero(mask[:, m_list[lo]])
                if not len(who):
                    continue
                near = tables if len(who) == len(x) else [t[:, who] for t in tables]
                for lo in range(lo, hi, 1024):
                    up = min(hi, lo + 1024)
                    j, i = np.nonzero(q.products(near, codes[lo:up]) >= least[lo:up, None] - to_centres[who, m_list[lo]])
                    if not len(i):
                        continue
                    dense = 16 * len(i) > len(who) * (up - lo)
                    i, j = who[i], j + lo
                    exact = (x @ m_x[lo:up].T)[i, j - lo] if dense else np.einsum("nd,nd->n", x[i], m_x[j])
                    hit = (exact >= s.threshold) & (q_id[a + i] != m_id[j])
                    if hit.any():
                        i, j = i[hit], j[hit]
                        np.add.at(count, a + i, m_n[j])
                        edges.append(np.unique(np.stack([np.searchsorted(ids, q_id[a + i]), np.searchsorted(ids, m_id[j])], 1), axis=0))
        hit = np.flatnonzero(count)
        if not len(hit):
            return empty
        root = ids[_spanning(len(ids), np.concatenate(edges))]
        moved = np.flatnonzero(root != ids)
        counted = pd.DataFrame({"rep": q_id[hit], "links": count[hit], "other": q_id[hit]})
        return pd.concat([counted, pd.DataFrame({"rep": ids[moved], "links": 0, "other": root[moved]})])

    keys = ["bundle", "slice"]
    return cut(
        held.select(*keys, "rep", "copies", "unit", "list", "code")
        .groupBy(*keys)
        .cogroup(asked.select(*[F.col(k).alias(f"q_{k}") for k in (*keys, "rep", "unit", "list")]).groupBy(*[f"q_{k}" for k in keys]))
        .applyInPandas(compare, _FOUND)
    )


def near_duplicates(embeddings: DataFrame, s: Settings = Settings()) -> DataFrame:
    """vec_id, n_links, component_id and kept: one row per row of ``embeddings``.

    ``n_links`` counts other rows whose cosine is at least the threshold; ``component_id`` is the
    smallest vec_id reachable by links. Rows with a null vec_id link with nothing and are kept.
    """
    spark = embeddings.sparkSession
    cut = Cut(spark)
    rows = cut(distinct_vectors(embeddings).withColumn("key", F.when(F.col("ok"), F.sha2(F.to_json("embedding"), 256))))
    reps = cut(
        rows.where("ok").groupBy("key").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.min_by("embedding", "vec_id").alias("embedding"))
    )
    # One row per width of vectors; only vectors of one width can be compared.
    widths = reps.groupBy(F.size("embedding").alias("width")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").collect()
    found = [_links(cut, reps.where(F.size("embedding") == w.width), w.width, w.n, s) for w in widths]
    found = reduce(DataFrame.unionByName, found) if found else spark.createDataFrame([], _FOUND)
    roots = connected_components(cut, found.where("rep <> other").select(F.col("rep").alias("a"), F.col("other").alias("b")))
    counts = found.groupBy("rep").agg(F.sum("links").alias("links"))
    named = (
        reps.select("key", "rep", "copies")
        .join(counts, "rep", "left")
        .join(roots.withColumnRenamed("v", "rep"), "rep", "left")
        .select("key", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n"), F.coalesce("root", "rep").alias("root"))
    )
    return (
        rows.select("vec_id", "key")
        .join(cut(named), "key", "left")
        .select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("root", "vec_id").alias("component_id"))
        .withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))
    )
