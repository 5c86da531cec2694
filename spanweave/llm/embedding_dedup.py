"""Near-duplicate vectors by product quantisation: inverted lists of residual codes, table-lookup distances, exact cosine rerank.

Two vectors are linked if their cosine, in double precision, is at least ``COSINE``; for unit vectors that is
a distance of at most r = sqrt(2 - 2 * COSINE). Centroids and codebooks are fitted on a bounded sample (``TRAIN_ROWS``);
every vector is indexed.

* Probes. x lies in the list of its nearest centroid a. For y and its nearest centroid b the bisector between a and b
  gives d(y,a)^2 - d(y,b)^2 <= 2 |a - b| t, where t is the part of x - y along a - b. t is at most r, and in D dimensions
  about r / sqrt(D) unless the difference points just there: y probes all lists that pass with t = r * min(1, SIGMAS /
  sqrt(D)). With four sigmas a link is lost by a chance below 1 in 1000 (the tests compare with brute force); an infinite
  ``sigmas`` loses none and probes most lists. The number of lists probed hardly grows with the number of lists.
* Codes. x is coded as its centroid plus a codeword of the residual in each subspace, with the error e of
  this copy kept. The looked-up distance of y to the copy is at most r + e if x is linked; others are skipped.
* Shipping. Lists close to each other share a cell; a vector is sent to a cell once, however many of its lists it probes.

What passes is reranked by exact cosine. Cells and their queries are cut into blocks of bounded size, and a block
emits counts per vector and a spanning forest of its links, never pairs. Equal vectors are one class.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing
(n_links 0, their own component); vectors of different length are not compared; repeated rows count as vectors
of their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spanweave.llm.batches import bounded_sample
from spanweave.operators.components import connected_components
from spanweave.session import stored

COSINE = 0.95
#: Documented bound of the training sample, in distinct vectors.
TRAIN_ROWS = 16_000
MOST_LISTS = 4096
SUBSPACES = 8
CODEWORDS = 64
#: Deviations of a random direction that probes allow for.
SIGMAS = 4.0
LISTS_A_CELL = 16
BLOCK_QUERIES, BLOCK_ENTRIES = 16_384, 4096


def kmeans(x: np.ndarray, k: int, rounds: int = 8, seed: int = 7) -> np.ndarray:
    """Centroids by Lloyd's rounds from k distinct rows; fewer rows give fewer centroids."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        at = nearest(x, c)
        n = np.bincount(at, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, at, x)
        c = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], c)
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return (2 * x @ c.T - (c * c).sum(1)).argmax(1)


class Quantizer:
    """Centroids, codebooks and the probing rule for unit vectors."""

    def __init__(
        self, sample: np.ndarray, lists: int, subspaces: int = SUBSPACES, codewords: int = CODEWORDS,
        cosine: float = COSINE, sigmas: float = SIGMAS,
    ):
        self.reach = float(np.sqrt(max(0.0, 2 - 2 * cosine))) + 1e-6
        self.cosine = cosine
        self.centroids = kmeans(sample, lists)
        rest = sample - self.centroids[nearest(sample, self.centroids)]
        self.cuts = np.linspace(0, sample.shape[1], min(subspaces, sample.shape[1]) + 1).astype(int)
        self.books = [kmeans(rest[:, a:b], codewords) for a, b in zip(self.cuts, self.cuts[1:])]
        self.along = self.reach * min(1.0, sigmas / sample.shape[1] ** 0.5)
        square = (self.centroids**2).sum(1)
        self.apart = np.sqrt(np.maximum(0, square[:, None] + square - 2 * self.centroids @ self.centroids.T))
        self.cell = nearest(self.centroids, kmeans(self.centroids, -(-len(self.centroids) // LISTS_A_CELL)))

    def index(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """List, codes and error of each row."""
        at = nearest(x, self.centroids)
        rest = x - self.centroids[at]
        codes = np.stack([nearest(rest[:, a:b], book) for a, b, book in zip(self.cuts, self.cuts[1:], self.books)], 1).astype(np.uint8)
        copy = np.concatenate([book[codes[:, m]] for m, book in enumerate(self.books)], 1)
        return at, codes, np.linalg.norm(rest - copy, axis=1)

    def probes(self, y: np.ndarray) -> np.ndarray:
        """rows x lists: which lists may hold a link of each row."""
        d = (y * y).sum(1)[:, None] + (self.centroids**2).sum(1) - 2 * y @ self.centroids.T
        own = d.argmin(1)
        return d - d[np.arange(len(y)), own][:, None] <= 2 * self.along * self.apart[own] + 1e-6

    def links(self, y: np.ndarray, x: np.ndarray, at: int, codes: np.ndarray, error: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """For each row of y that has any, the rows of list ``at`` with a cosine of at least the threshold."""
        rest = y - self.centroids[at]
        most = ((self.reach + error) ** 2 + 1e-4).astype(np.float32)[:, None]
        tables, codes = [], codes.astype(np.intp)
        for m, (a, b) in enumerate(zip(self.cuts, self.cuts[1:])):
            part, book = rest[:, a:b], self.books[m]
            tables.append(((book * book).sum(1)[:, None] + (part * part).sum(1) - 2 * book @ part.T).astype(np.float32))
        total, more = np.empty((len(x), 256), np.float32), np.empty((len(x), 256), np.float32)
        for start in range(0, len(y), 256):  # rows of the tables are copied whole, entries by queries, and stay in cache
            some = slice(start, min(len(y), start + 256))
            t, u = (z if some.stop - start == 256 else np.empty((len(x), some.stop - start), np.float32) for z in (total, more))
            np.take(np.ascontiguousarray(tables[0][:, some]), codes[:, 0], axis=0, out=t, mode="clip")
            for m in range(1, len(tables)):
                np.take(np.ascontiguousarray(tables[m][:, some]), codes[:, m], axis=0, out=u, mode="clip")
                t += u
            entry, query = np.nonzero(t <= most)
            order = np.argsort(query, kind="stable")
            entry, query = entry[order], query[order]
            for rows in np.split(np.arange(len(query)), np.flatnonzero(np.diff(query)) + 1):
                if len(rows):
                    i, near = start + int(query[rows[0]]), entry[rows]
                    good = near[x[near] @ y[i] >= self.cosine]
                    if len(good):
                        yield i, good


def classes(vectors: DataFrame) -> DataFrame:
    """vec_id, v (null unless valid), h1, h2 of each row; equal valid vectors share the hashes."""
    v = F.col("embedding")
    sound = v.isNotNull() & ~F.coalesce(F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False)) & F.coalesce(F.exists(v, lambda x: x != 0), F.lit(False))
    rows = vectors.select("vec_id", F.when(sound, v).alias("v"))
    return rows.withColumn("h1", F.xxhash64("v")).withColumn("h2", F.xxhash64(F.reverse("v"), F.lit(1)))


def _unit(raw: list[bytes], kind: str) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1).astype(np.float64)
    x = x / np.abs(x).max(1)[:, None]
    return x / np.linalg.norm(x, axis=1)[:, None]


def _one_length(
    known: DataFrame, kind: str, *, cosine: float, train_rows: int, lists: int | None, sigmas: float
) -> DataFrame:
    """(kind, a, b) of classes of one length: kind 0 - a has b links in a block; kind 1 - a and b are linked."""
    n = known.count()
    rows = bounded_sample(known.select("rep", "v"), train_rows, "rep").orderBy("rep").select("v").collect()
    sample = _unit([np.array(r["v"], kind).tobytes() for r in rows], kind)
    lists = lists or int(np.clip(round(n**0.5), 1, MOST_LISTS))
    shared = known.sparkSession.sparkContext.broadcast(Quantizer(sample, lists, cosine=cosine, sigmas=sigmas))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            values = b.column("v").flatten().to_numpy(zero_copy_only=False).astype(kind).reshape(b.num_rows, -1)
            raw = [row.tobytes() for row in values]
            x = _unit(raw, kind)
            at, codes, error = q.index(x)
            row, which = np.nonzero(q.probes(x))
            cells = np.unique(np.stack([row, q.cell[which]], 1), axis=0)
            ends = np.searchsorted(cells[:, 0], np.arange(b.num_rows + 1)).astype(np.int32)
            yield pa.record_batch(
                [
                    b.column("rep"), b.column("n"), pa.array(raw, pa.binary()), pa.array(at.astype(np.int32)),
                    pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(error), pa.array(q.cell[at].astype(np.int32)),
                    pa.ListArray.from_arrays(ends, cells[:, 1].astype(np.int32)),
                ],
                names=["rep", "n", "raw", "list", "codes", "error", "cell", "cells"],
            )

    schema = "rep long, n long, raw binary, list int, codes binary, error double, cell int, cells array<int>"
    index = stored(known.select("rep", "n", "v").mapInArrow(run, schema), "index")
    queries = index.select("rep", "raw", F.explode("cells").alias("cell"))
    entries = index.select("rep", "n", "raw", "list", "codes", "error", "cell")
    # one row per cell: how many blocks its entries and its queries are cut into
    pieces = lambda df, rows, name: df.groupBy("cell").agg(F.ceil(F.count(F.lit(1)) / rows).cast("int").alias(name))
    cut = stored(pieces(entries, BLOCK_ENTRIES, "parts").join(pieces(queries, BLOCK_QUERIES, "groups"), "cell"), "cuts")
    cut = F.broadcast(cut)  # at most MOST_LISTS rows
    every = lambda c: F.explode(F.sequence(F.lit(0), F.col(c) - 1))
    left = entries.join(cut, "cell").withColumn("i", F.pmod(F.xxhash64("rep"), "parts").cast("int")).withColumn("j", every("groups"))
    right = queries.join(cut, "cell").withColumn("j", F.pmod(F.xxhash64("rep", F.lit(2)), "groups").cast("int"))
    right = right.withColumn("i", every("parts"))
    columns = ["cell", "i", "j", "rep", "n", "raw", "list", "codes", "error"]
    both = left.select(*columns).unionByName(right.select("cell", "i", "j", "rep", "raw"), allowMissingColumns=True)

    def block(table: pa.Table) -> pa.Table:
        is_entry = table.column("codes").is_valid().to_numpy()
        e, y = table.filter(pa.array(is_entry)), table.filter(pa.array(~is_entry))
        none = pa.table({"kind": pa.array([], pa.int32()), "a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        if not e.num_rows or not y.num_rows:
            return none
        x_id, y_id, weight = e.column("rep").to_numpy(), y.column("rep").to_numpy(), e.column("n").to_numpy()
        codes = np.frombuffer(b"".join(e.column("codes").to_pylist()), np.uint8).reshape(e.num_rows, -1)
        found, root = [], {}

        def top(k: int) -> int:
            while root.setdefault(k, k) != k:
                root[k] = root[root[k]]
                k = root[k]
            return k

        q = shared.value
        xs, ys = _unit(e.column("raw").to_pylist(), kind), _unit(y.column("raw").to_pylist(), kind)
        at, error = e.column("list").to_numpy(), e.column("error").to_numpy()
        asked = q.probes(ys)
        for one in np.unique(at):
            mine, asking = np.flatnonzero(at == one), np.flatnonzero(asked[:, one])
            for i, good in q.links(ys[asking], xs[mine], int(one), codes[mine], error[mine]):
                me, good = int(y_id[asking[i]]), mine[good]
                good = good[x_id[good] != me]
                if len(good):
                    found.append((0, me, int(weight[good].sum())))
                    for k in x_id[good].tolist():
                        a, b = top(me), top(k)
                        if a != b:
                            root[max(a, b)] = min(a, b)
        found += [(1, k, top(k)) for k in list(root) if top(k) != k]
        if not found:
            return none
        what, a, b = zip(*found)
        return pa.table({"kind": pa.array(what, pa.int32()), "a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return both.groupBy("cell", "i", "j").applyInArrow(block, "kind int, a long, b long")


def find(
    vectors: DataFrame, *, cosine: float = COSINE, train_rows: int = TRAIN_ROWS, lists: int | None = None, sigmas: float = SIGMAS
) -> DataFrame:
    """vec_id, n_links, component_id, kept of each row."""
    spark = vectors.sparkSession
    element = vectors.schema["embedding"].dataType.elementType
    kind = "<f4" if isinstance(element, T.FloatType) else "<f8"
    rows = classes(vectors.select("vec_id", "embedding"))
    valid = rows.filter("v is not null")
    known = stored(valid.groupBy("h1", "h2").agg(F.min(F.struct("vec_id", "v")).alias("x"), F.count(F.lit(1)).alias("n")).select("h1", "h2", F.col("x.vec_id").alias("rep"), "x.v", "n"), "vectors")
    found = spark.createDataFrame([], "kind int, a long, b long")
    for row in known.select(F.size("v").alias("d")).distinct().collect():  # lengths of vectors, normally one
        options = {"cosine": cosine, "train_rows": train_rows, "lists": lists, "sigmas": sigmas}
        found = found.unionByName(_one_length(known.filter(F.size("v") == row["d"]), kind, **options))
    found = stored(found, "found")
    links = found.filter("kind = 0").groupBy(F.col("a").alias("_a")).agg(F.sum("b").alias("links"))
    parts = connected_components(found.filter("kind = 1"))
    result = known.select("h1", "h2", "rep", "n").join(links, F.col("rep") == F.col("_a"), "left").join(parts, F.col("rep") == F.col("node"), "left")
    result = stored(result.select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id")), "classes")
    out = valid.select("vec_id", "h1", "h2").join(result, ["h1", "h2"]).select("vec_id", "n_links", "component_id")
    alone = rows.filter("v is null").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return out.unionByName(alone).withColumn("kept", F.col("vec_id") == F.col("component_id"))
