"""Packing of documents into token sequences: repeat counts of window fillings by non-negative least squares.

Documents become ids plus an end id and are cut into windows; what remains (shorter than a
window) is counted in a histogram by length, which has fewer bins than the window has tokens.
The driver plans on that histogram alone: it enumerates fillings of a window by up to four
lengths, solves for non-negative repeat counts that reproduce the histogram best, rounds them
down to what is there, and packs the rest greedily, longest first. The plan is a short list of
(length, first rank, sequence, offset) ranges; pieces find their place by their rank among
pieces of equal length, which comes from counts per task and length, so no group is gathered.

Defined cases: null and empty texts are documents of the end id alone; repeated rows are packed
each; an empty table gives no pieces; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from spanweave.llm import tokens
from spanweave.llm.batches import slices
from spanweave.session import stored

WINDOW = 2048
END_ID = 1
PIECE = "doc_id long, start long, length int, ids_crc32 long, doc_tokens long, task int, rank long"


def cut(docs: DataFrame, *, window: int = WINDOW, end_id: int = END_ID, path: str | None = None, keep_ids: bool = False) -> DataFrame:
    """Pieces of every document with their task and their rank in that task among pieces of equal length; ``keep_ids`` adds the ids."""
    path = path or tokens.default_path()

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, seen = TaskContext.get().partitionId(), np.zeros(window + 1, np.int64)
        for part in slices(batches):
            rows: list[tuple] = []
            for i, text in enumerate(part.column("text").to_pylist()):
                ids = np.append(tokens.encode(text or "", path), np.array([end_id], "<u4"))
                for start in range(0, len(ids), window):
                    piece = ids[start : start + window]
                    rows.append((i, start, len(piece), zlib.crc32(piece.tobytes()), len(ids), task, seen[len(piece)], piece))
                    seen[len(piece)] += 1
            where, start, length, crc, total, tasks, rank, pieces = zip(*rows)
            columns = [part.column("doc_id").take(pa.array(where)), pa.array(start, pa.int64()), pa.array(length, pa.int32()), pa.array(crc, pa.int64()), pa.array(total, pa.int64()), pa.array(tasks, pa.int32()), pa.array(rank, pa.int64())]
            if keep_ids:
                columns.append(pa.array(pieces, pa.list_(pa.int64())))
            yield pa.record_batch(columns, names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "task", "rank", *["ids"] * keep_ids])

    return docs.select("doc_id", "text").mapInArrow(run, PIECE + ", ids array<long>" * keep_ids)


def fillings(histogram: np.ndarray, window: int = WINDOW, *, breadth: int = 24, slack: float = 0.004) -> np.ndarray:
    """Combinations of up to four present lengths (0: none) that fill the window up to ``slack``, each as a sorted row.

    For every present length, partners are tried at ``breadth`` quantiles of the histogram, and the last place takes
    the longest present length that fits."""
    present = np.flatnonzero(histogram)
    if not len(present):
        return np.zeros((0, 4), np.int64)
    fits = np.zeros(window + 1, np.int64)  # the longest present length up to each bound
    fits[present] = present
    fits = np.maximum.accumulate(fits)
    mass = np.cumsum(histogram[present])
    probes = np.unique(present[np.searchsorted(mass, mass[-1] * (np.arange(breadth) + 0.5) / breadth)])
    a = present
    made = [np.stack([a, fits[window - a], 0 * a, 0 * a], 1)]
    ab = np.stack(np.meshgrid(present, probes, indexing="ij"), -1).reshape(-1, 2)
    ab = ab[ab.sum(1) < window]
    if len(ab):
        made.append(np.column_stack([ab, fits[window - ab.sum(1)], 0 * ab[:, 0]]))
        few = probes[:: max(1, len(probes) // 6)]
        abc = np.column_stack([np.repeat(ab, len(few), 0), np.tile(few, len(ab))])
        abc = abc[abc.sum(1) < window]
        if len(abc):
            made.append(np.column_stack([abc, fits[window - abc.sum(1)]]))
    rows = np.concatenate(made)
    # besides full fillings, the best ones of each length, so that a length without exact partners is not left over
    first, waste = rows[:, 0], window - rows.sum(1)
    order = np.lexsort((waste, first))
    place = np.arange(len(rows)) - np.searchsorted(first[order], first[order])
    keep = waste <= window * slack
    keep[order[place < 4]] = True
    return np.unique(np.sort(rows[keep], 1), axis=0)


def solve_counts(rows: np.ndarray, histogram: np.ndarray, steps: int = 400) -> np.ndarray:
    """x >= 0 that brings the lengths used by x repeats of each filling closest to the histogram: accelerated projected gradient."""
    if not len(rows):
        return np.zeros(0)
    size, used = len(histogram), rows > 0
    apply = lambda x: np.bincount(rows.ravel(), np.repeat(x, rows.shape[1]), size) * live
    live = np.ones(size)
    live[0] = 0
    # relative misfit, so that rare lengths count too, and more for long ones, which are the harder to place later
    weight = (np.arange(size) / size) ** 2 / np.maximum(1.0, histogram)
    degree = np.bincount(rows[used], minlength=size)
    bound = max(1e-12, float((np.where(used, (weight * degree)[rows], 0).sum(1) * rows.shape[1]).max()))
    x = y = np.zeros(len(rows))
    momentum = 1.0
    for _ in range(steps):
        misfit = (apply(y) - histogram) * weight * live
        new = np.maximum(0, y - np.where(used, misfit[rows], 0).sum(1) / bound)
        after = (1 + np.sqrt(1 + 4 * momentum**2)) / 2
        y = new + (momentum - 1) / after * (new - x)
        x, momentum = new, after
    return x


def plan(histogram: np.ndarray, window: int = WINDOW) -> tuple[np.ndarray, int]:
    """Ranges (length, first rank, first sequence, offset, repeats) that place every remainder; how many sequences. ``histogram[n]``: remainders of length n."""
    left = histogram.astype(np.int64).copy()
    left[0] = 0
    cursor, ranges, sequences = np.zeros(len(left), np.int64), [], 0

    def use(lengths: list[int], repeats: int) -> None:
        nonlocal sequences
        offset = 0
        for n in lengths:
            # equal lengths in one filling take ranks one range after the other
            ranges.append((n, cursor[n], sequences, offset, repeats))
            cursor[n] += repeats
            left[n] -= repeats
            offset += n
        sequences += repeats

    def most(lengths: list[int]) -> int:
        return min(int(left[n]) // lengths.count(n) for n in set(lengths))

    rows = fillings(left, window)
    counts = solve_counts(rows, left)
    for k in np.argsort(-counts, kind="stable"):
        if counts[k] < 1:
            break
        lengths = [int(n) for n in rows[k] if n][::-1]
        if (repeats := min(int(counts[k]), most(lengths))) > 0:
            use(lengths, repeats)
    while left.any():
        present = np.flatnonzero(left)
        lengths, space = [], window
        while len(fit := present[present <= space]):
            n = next((int(n) for n in fit[::-1] if left[n] > lengths.count(int(n))), 0)
            if not n:
                break
            lengths.append(n)
            space -= n
        use(lengths, most(lengths))
    return np.array(ranges, np.int64).reshape(-1, 5), sequences


def pack(docs: DataFrame, *, window: int = WINDOW, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset of every piece."""
    pieces = stored(cut(docs, window=window, end_id=end_id, path=path), "pieces")
    full, rest = pieces.filter(F.col("length") == window), pieces.filter(F.col("length") < window)
    counts = rest.groupBy("task", "length").agg(F.count(F.lit(1)).alias("n"))
    histogram = np.zeros(window, np.int64)
    for row in counts.groupBy("length").agg(F.sum("n").alias("n")).collect():  # fewer rows than the window has tokens
        histogram[row["length"]] = row["n"]
    ranges, sequences = plan(histogram, window)
    ranges = ranges[np.lexsort((ranges[:, 1], ranges[:, 0]))]
    before = F.sum("n").over(Window.partitionBy("length").orderBy("task").rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select("task", "length", F.coalesce(before, F.lit(0)).alias("before"))
    ranked = rest.join(offsets, ["task", "length"]).select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("rank") + F.col("before")).alias("rank"))
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

    def place(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        first = ranges[:, 0] * (1 << 50) + ranges[:, 1]
        for b in batches:
            length, rank = b.column("length").to_numpy(), b.column("rank").to_numpy()
            at = np.searchsorted(first, length.astype(np.int64) * (1 << 50) + rank, side="right") - 1
            sequence = ranges[at, 2] + rank - ranges[at, 1]
            yield pa.record_batch([*(b.column(n) for n in names[:2]), pa.array(length.astype(np.int64)), *(b.column(n) for n in names[3:5]), pa.array(sequence), pa.array(ranges[at, 3])], names=names)

    placed = ranked.mapInArrow(place, ", ".join(f"{n} long" for n in names))
    # a whole window is a sequence by itself, numbered after the others by its task and its rank there
    whole = full.select(
        "doc_id", "start", F.col("length").cast("long").alias("length"), "ids_crc32", "doc_tokens",
        (F.lit(sequences) + F.shiftleft(F.col("task").cast("long") + 1, 40) + F.col("rank")).alias("sequence_id"), F.lit(0).cast("long").alias("offset"),
    )
    return placed.unionByName(whole)


def padding(placed: DataFrame, window: int = WINDOW) -> DataFrame:
    """sequences, tokens, padded (tokens with padding to the window, none at a power of two), share of padding."""
    used = placed.groupBy("sequence_id").agg(F.sum("length").alias("used"))
    is_power = F.bit_count(F.col("used")) == 1
    return used.agg(
        F.count(F.lit(1)).alias("sequences"), F.sum("used").alias("tokens"), F.sum(F.when(is_power, F.col("used")).otherwise(F.lit(window))).alias("padded")
    ).withColumn("share", F.lit(1.0) - F.col("tokens") / F.col("padded"))
