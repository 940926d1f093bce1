"""Embedding near-duplicates by product quantisation.

A coarse quantiser deals the vectors of each label to inverted lists; a vector's residual is kept as one code per
subspace, with the length of what the codes miss. Each vector probes the lists nearest to it: a table of the squared
distances from its residual to all subspace centroids gives the distance to every code of a list, and since the missed
length is known, a candidate is dropped only if the triangle inequality proves it too far. What is left is reranked by
the exact cosine in double precision.

Equal vectors of a label are one class with a count. Lists are cut into member and query blocks of bounded size, so a
list that holds most rows is many cells; a cell returns sums per vector and a spanning star per local component, never
its pairs. A pair found by one side only is credited to both.

Only the quantiser is fitted on a sample, of at most SAMPLE_BYTES; every row is indexed. A link is missed only if
neither vector's PROBES lists hold the other.

Results for odd input: rows with a null label or with vectors that are null, empty, zero, or hold null or non-finite
components link with nothing and are kept; vectors of different lengths don't link; rows that repeat are vectors of
their own; an empty table gives an empty result; a null vec_id counts as a vector and gets a null component; other
columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import connected_components
from .shared import discard, materialize, prepare_workers

SAMPLE_BYTES = 16 << 20  # of vectors that the quantiser is fitted on
LIST_ROWS = 256  # vectors a list should hold
MOST_LISTS = 4096  # bounds the centroids that go to every task
PROBES = 16
SUBSPACES, CODES = 8, 64
MEMBERS, QUERIES = 512, 1024  # rows of a cell


def kmeans(x: np.ndarray, k: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centres = x[rng.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        near = nearest(x, centres, 1)[:, 0]
        counts = np.bincount(near, minlength=len(centres))
        sums = np.zeros_like(centres)
        np.add.at(sums, near, x)
        centres[counts > 0] = sums[counts > 0] / counts[counts > 0, None]
    return centres


def nearest(x: np.ndarray, centres: np.ndarray, n: int) -> np.ndarray:
    """Numbers of the n nearest centres of each row, nearest first."""
    out = []
    for a in range(0, len(x), 4096):
        d = (centres**2).sum(1) - 2 * x[a : a + 4096] @ centres.T
        some = np.argpartition(d, n - 1, 1)[:, :n] if n < len(centres) else np.tile(np.arange(len(centres)), (len(d), 1))
        out.append(np.take_along_axis(some, np.argsort(np.take_along_axis(d, some, 1), 1, kind="stable"), 1))
    return np.concatenate(out) if out else np.zeros((0, n), np.int64)


@dataclass
class Quantiser:
    centres: np.ndarray  # lists x dimensions
    codebooks: np.ndarray  # subspaces x codes x width

    @classmethod
    def fit(cls, sample: np.ndarray, lists: int) -> Quantiser:
        centres = kmeans(sample, min(lists, len(sample)))
        rest = cls._split(sample - centres[nearest(sample, centres, 1)[:, 0]])
        return cls(centres, np.stack([kmeans(rest[:, s], min(CODES, len(sample))) for s in range(SUBSPACES)]))

    @staticmethod
    def _split(x: np.ndarray) -> np.ndarray:
        width = -(-x.shape[1] // SUBSPACES)
        return np.pad(x, ((0, 0), (0, width * SUBSPACES - x.shape[1]))).reshape(len(x), SUBSPACES, width)

    def encode(self, x: np.ndarray, lists: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(codes, length of what the codes miss)."""
        rest = self._split(x - self.centres[lists])
        codes = np.stack([nearest(rest[:, s], self.codebooks[s], 1)[:, 0] for s in range(SUBSPACES)], 1)
        seen = self.codebooks[np.arange(SUBSPACES), codes]
        return codes.astype(np.uint8), np.sqrt(((rest - seen) ** 2).sum((1, 2)))

    def distances(self, queries: np.ndarray, number: int, codes: np.ndarray) -> np.ndarray:
        """Squared distances from queries to coded members of one list, by table look-up."""
        rest = self._split(queries - self.centres[number])
        out = np.zeros((len(queries), len(codes)))
        for s in range(SUBSPACES):
            table = ((rest[:, s, None, :] - self.codebooks[s]) ** 2).sum(2)
            out += table[:, codes[:, s]]
        return out


def unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x**2).sum(1, keepdims=True))


def _matrix(column, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), "<f8").reshape(-1, width)


INDEX = "rep long, list int, probes array<int>, codes binary, missed double"


def _index(quantisers: dict[int, Quantiser]):
    def run(batches):
        for batch in batches:
            widths = np.asarray(batch.column("width"))
            for width in np.unique(widths):
                own = batch.filter(pa.array(widths == width))
                q = quantisers[int(width)]
                x = unit(_matrix(own.column("vector"), int(width)))
                probes = nearest(x, q.centres, min(PROBES, len(q.centres)))
                codes, missed = q.encode(x, probes[:, 0])
                yield pa.RecordBatch.from_arrays(
                    [own.column("rep"), pa.array(probes[:, 0], pa.int32()), pa.array(list(probes.astype(np.int32)), pa.list_(pa.int32())), pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(missed)],
                    ["rep", "list", "probes", "codes", "missed"],
                )

    return run


def local_stars(ids: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest id of its component) for the nodes that the links between positions a and b touch."""
    least = ids.copy()
    while True:
        before = least.copy()
        low = np.minimum(least[a], least[b])
        np.minimum.at(least, a, low)
        np.minimum.at(least, b, low)
        if (before == least).all():
            break
    touched = np.unique(np.concatenate([a, b]))
    return ids[touched], least[touched]


def _cell(quantisers: dict[int, Quantiser], cosine: float):
    reach = np.sqrt(max(0.0, 2 - 2 * cosine))

    def run(cell: pa.Table) -> pa.Table:
        width, number = cell["width"][0].as_py(), cell["cell_list"][0].as_py()
        is_query = np.asarray(cell["is_query"], dtype=bool)
        query, member = cell.filter(pa.array(is_query)), cell.filter(pa.array(~is_query))
        out = {"node": [], "links": [], "low": []}
        if len(query) and len(member):
            q = quantisers[width]
            xq, xm = unit(_matrix(query["vector"], width)), unit(_matrix(member["vector"], width))
            iq, im = np.asarray(query["rep"]), np.asarray(member["rep"])
            wq, wm = np.asarray(query["weight"]), np.asarray(member["weight"])
            codes = np.frombuffer(b"".join(member["codes"].to_pylist()), np.uint8).reshape(len(member), SUBSPACES)
            bound = (reach + np.asarray(member["missed"]) + 1e-9) ** 2
            # lists that the member probes itself: there it finds the query on its own
            home = np.asarray(query["list"])
            probed = np.zeros((len(member), len(q.centres)), bool)
            for row, own in enumerate(member["probes"].to_pylist()):
                probed[row, own] = True
            found = []
            for a in range(0, len(xq), 256):
                near = q.distances(xq[a : a + 256], number, codes) <= bound
                at, to = np.nonzero(near & (iq[a : a + 256, None] != im))
                for c in range(0, len(at), 50_000):
                    i, j = at[c : c + 50_000] + a, to[c : c + 50_000]
                    linked = (xq[i] * xm[j]).sum(1) >= cosine
                    found.append((i[linked], j[linked]))
            i, j = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, int),) * 2
            alone = ~probed[j, home[i]]
            links = [np.bincount(i, wm[j], len(iq)), np.bincount(j[alone], wq[i[alone]], len(im))]
            ids, back = np.unique(np.concatenate([iq, im]), return_inverse=True)
            total = np.bincount(back, np.concatenate(links), len(ids)).astype(np.int64)
            nodes, low = local_stars(ids, back[: len(iq)][i], back[len(iq) :][j])
            out = {"node": nodes, "links": total[np.searchsorted(ids, nodes)], "low": low}
        return pa.table({k: pa.array(v, pa.int64()) for k, v in out.items()})

    return run


def near_duplicates(vectors: DataFrame, cosine: float = 0.93) -> DataFrame:
    """vectors (vec_id, embedding, label) -> vec_id, n_links, component_id, kept."""
    spark = vectors.sparkSession
    prepare_workers(spark)
    v = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").alias("label"), F.col("embedding").cast("array<double>").alias("embedding"))
    usable = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists("embedding", lambda x: x != 0)
    v = v.withColumn("usable", F.coalesce(F.col("label").isNotNull() & F.col("vec_id").isNotNull() & usable, F.lit(False)))
    rows = v.where("usable")
    classes = rows.groupBy("label", "embedding").agg(F.min("vec_id").alias("rep"), F.count("*").alias("weight"))
    classes = materialize(classes.withColumn("width", F.size("embedding")), "classes")
    quantisers = _fit(classes)
    packed = classes.mapInArrow(_packed, "rep long, weight long, width int, vector binary")
    index = materialize(packed.mapInArrow(_index(quantisers), INDEX).join(packed, "rep").join(classes.select("rep", "label"), "rep"), "index")
    probing = index.select("rep", "label", "weight", "width", "vector", "list", F.explode("probes").alias("cell_list"))
    sizes = index.groupBy("label", "width", F.col("list").alias("cell_list")).agg(F.count("*").alias("members"))
    asked = probing.groupBy("label", "width", "cell_list").agg(F.count("*").alias("queries"))
    sizes = materialize(sizes.join(asked, ["label", "width", "cell_list"]).withColumn("mb", F.ceil(F.col("members") / MEMBERS).cast("int")).withColumn("qb", F.ceil(F.col("queries") / QUERIES).cast("int")), "lists")
    spot = F.xxhash64("rep", F.lit(17))
    member = index.withColumn("cell_list", F.col("list")).join(sizes, ["label", "width", "cell_list"])
    member = member.select("label", "width", "cell_list", F.pmod(spot, "mb").cast("int").alias("m"), F.explode(F.sequence(F.lit(0), F.col("qb") - 1)).alias("q"), F.lit(False).alias("is_query"), "rep", "weight", "vector", "list", "probes", "codes", "missed")
    query = probing.join(sizes, ["label", "width", "cell_list"])
    query = query.select("label", "width", "cell_list", F.explode(F.sequence(F.lit(0), F.col("mb") - 1)).alias("m"), F.pmod(spot, "qb").cast("int").alias("q"), F.lit(True).alias("is_query"), "rep", "weight", "vector", "list", F.lit(None).cast("array<int>").alias("probes"), F.lit(None).cast("binary").alias("codes"), F.lit(None).cast("double").alias("missed"))
    cells = member.unionByName(query).groupBy("label", "width", "cell_list", "m", "q")
    found = materialize(cells.applyInArrow(_cell(quantisers, cosine), "node long, links long, low long"), "found")
    links = found.groupBy(F.col("node").alias("rep")).agg(F.sum("links").alias("links"))
    components = connected_components(found.select(F.col("node").alias("u"), F.col("low").alias("v"))).withColumnRenamed("node", "rep")
    of_class = classes.join(links, "rep", "left").join(components, "rep", "left")
    of_class = of_class.select("label", "embedding", (F.col("weight") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    linked = rows.select("vec_id", "label", "embedding").join(of_class, ["label", "embedding"]).select("vec_id", "n_links", "component_id")
    alone = v.where("not usable").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    out = linked.unionByName(alone)
    discard(index, sizes)
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def _packed(batches):
    for batch in batches:
        vectors = [np.array(x, "<f8").tobytes() for x in batch.column("embedding").to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column("rep"), batch.column("weight"), batch.column("width"), pa.array(vectors, pa.binary())], ["rep", "weight", "width", "vector"])


def _fit(classes: DataFrame) -> dict[int, Quantiser]:
    """A quantiser for each vector length, fitted on a sample of bounded size drawn by hash."""
    out = {}
    for row in classes.groupBy("width").agg(F.count("*").alias("n")).collect():
        most = max(1, SAMPLE_BYTES // (8 * row["width"]))
        sample = classes.where(F.col("width") == row["width"]).orderBy(F.xxhash64("rep", F.lit(3)), "rep").limit(most).select("embedding").toPandas()
        x = unit(np.array(sample["embedding"].tolist(), float))
        out[row["width"]] = Quantiser.fit(x, min(MOST_LISTS, -(-row["n"] // LIST_ROWS)))
    return out
