"""Benchmark passages in documents by shared character q-grams in diagonal bands, verified by banded alignment.

Texts are folded (lower case; runs of other than letters and digits become one space). Every benchmark item is
cut into segments of ``SEGMENT`` characters, half overlapping, each with an edit budget of ``EDIT_SHARE``.
A place that aligns with a segment of m characters within e edits shares at least m + 1 - q(e + 1) of
its q-grams with it, all on neighbouring diagonals (place in the text less place in the segment). So the
shared q-grams are counted in overlapping bands of diagonals, bands that reach the bound are
aligned within the band, and those within the budget are kept. Nothing that meets the budget is lost.

The benchmark goes to the executors in blocks of ``BLOCK_CHARS`` characters. If there are several, one pass over the
documents first looks for places dense in q-grams of any block, by a bit map of all of them (``GATE_BITS`` at most, put
together by the executors): only documents with such a place are searched for the blocks. Documents are never shuffled.
An excerpt of an item is found wherever it lies if it has at least one and a half segments' characters.

Defined cases: null and empty texts match nothing; items of fewer than ``LEAST`` folded characters never
match; equal items each match; rows with one doc_id are merged to one row per (doc_id, item_id); extra
columns are ignored, and in ``clean`` kept, where each row is judged by itself.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from spanweave.llm.batches import codepoints, slices
from spanweave.session import stored

Q = 10
SEGMENT = 80
EDIT_SHARE = 0.075
LEAST = 24
BLOCK_CHARS = 1_000_000
GATE_BITS = 1 << 28
#: Bytes of text searched at once where texts are passed on.
PASSED = 500_000
_SPACE = 32
_BITS = 23


@cache
def fold_table() -> np.ndarray:
    """Lower case of letters and digits by codepoint, 0 for everything else."""
    table = np.zeros(0x110000, np.uint32)
    for c in (*range(0x3400), *range(0xA000, 0xD800), *range(0xF900, 0x20000)):
        if (ch := chr(c)).isalnum():
            table[c] = ord(low) if len(low := ch.lower()) == 1 else c
    for a, b in ((0x3400, 0xA000), (0x20000, 0x32000)):
        table[a:b] = np.arange(a, b)
    return table


def fold(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Folded characters and where each stood."""
    low = fold_table()[points]
    keep = low > 0
    keep[1:] |= keep[:-1].copy()
    at = np.flatnonzero(keep)
    low = low[at]
    low[low == 0] = _SPACE
    return low, at


def grams(x: np.ndarray, q: int = Q) -> np.ndarray:
    """A 64-bit number for each q-gram by its first place; built from runs of doubled length."""
    if len(x) < q:
        return np.zeros(0, np.uint64)
    base, out, have = np.uint64(0x9E3779B97F4A7C15), None, 0
    run, size, power = x.astype(np.uint64) + np.uint64(1), 1, base
    rest = q
    while rest:
        if rest & 1:
            n = len(x) - have - size + 1
            out = run if out is None else out[:n] * power + run[have : have + n]
            have += size
        rest >>= 1
        if rest:
            run = run[: len(run) - size] * power + run[size:]
            with np.errstate(over="ignore"):
                size, power = 2 * size, power * power
    out = out[: len(x) - q + 1]
    out = out ^ (out >> np.uint64(29))
    return out * np.uint64(0xBF58476D1CE4E5B9)


def budget(m: int, share: float = EDIT_SHARE, q: int = Q) -> int:
    """Edits allowed in m characters: ``share`` of them, fewer where the q-gram bound would fall below 2."""
    e = int(share * m)
    while e and m + 1 - q * (e + 1) < 2:
        e -= 1
    return e


def dense(hit: np.ndarray, reach: int, need: int) -> np.ndarray:
    """The hits that lie with ``need`` of them within ``reach`` places."""
    total = np.concatenate([[0], np.cumsum(hit)])
    at = np.flatnonzero(hit)
    ends = np.minimum(at + reach, len(hit))
    enough = np.zeros(len(hit) + 1, np.int64)
    good = at[total[ends] - total[at] >= need]
    np.add.at(enough, good, 1)
    np.add.at(enough, np.minimum(good + reach, len(hit)), -1)
    return at[np.cumsum(enough)[at] > 0]


def laid_out(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    """Folded texts end to end (0 parts them, so no q-gram across them is in an index), their beginnings, their places."""
    folded = [fold(codepoints(t or "")) for t in texts]
    ends = np.cumsum([0] + [len(f) + 1 for f, _ in folded])
    low = np.zeros(ends[-1], np.uint32)
    for (f, _), at in zip(folded, ends):
        low[at : at + len(f)] = f
    return low, ends, [at for _, at in folded]


class Gate:
    """Whether a text has a place dense in q-grams of the whole benchmark, by a bit map of them."""

    def __init__(self, words: np.ndarray, segment: int = SEGMENT, share: float = EDIT_SHARE, q: int = Q):
        self.words, self.q = words, q
        self.reach = segment + 2 * max(1, int(share * segment))
        sizes = range(max(LEAST, q), segment + 1)
        self.need = min(max(1, m + 1 - q * (budget(m, share, q) + 1)) for m in sizes)

    @classmethod
    def of(cls, benchmark: DataFrame, most_bits: int = GATE_BITS) -> Gate:
        chars = benchmark.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0
        bits = min(most_bits, 1 << max(16, int(16 * chars).bit_length()))

        def mark(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in slices(batches, limit=2_000_000):
                at = np.unique(grams(laid_out(part.column("text").to_pylist())[0]) % np.uint64(bits))
                word, where = np.unique(at >> np.uint64(6), return_inverse=True)
                value = np.zeros(len(word), np.uint64)
                np.bitwise_or.at(value, where, np.uint64(1) << (at & np.uint64(63)))
                yield pa.record_batch([pa.array(word.view(np.int64)), pa.array(value.view(np.int64))], names=["word", "value"])

        rows = benchmark.select("text").mapInArrow(mark, "word long, value long").groupBy("word").agg(F.bit_or("value").alias("value"))
        rows = rows.toArrow()  # bits / 64 rows at most
        table = np.zeros(bits // 64, np.uint64)
        table[rows.column("word").to_numpy()] = rows.column("value").to_numpy().view(np.uint64)
        return cls(table)

    def open(self, texts: list[str | None]) -> np.ndarray:
        """Which texts may hold a segment."""
        low, ends, _ = laid_out(texts)
        at = grams(low, self.q) % np.uint64(64 * len(self.words))
        hit = (self.words[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1) > 0
        out = np.zeros(len(texts), bool)
        out[np.searchsorted(ends, dense(hit, self.reach, self.need), side="right") - 1] = True
        return out


class Index:
    """Segments of some benchmark items and the places of their q-grams."""

    def __init__(self, items: Iterable[tuple[int, str | None]], segment: int = SEGMENT, share: float = EDIT_SHARE, q: int = Q):
        # bands of twice the edit budget, each beginning in the middle of the one before: any run of budget + 1 diagonals lies in one
        self.q, self.half = q, max(1, int(share * segment))
        segs: list[np.ndarray] = []
        owner: list[int] = []
        for item, text in items:
            low, _ = fold(codepoints(text or ""))
            low = low[:-1] if len(low) and low[-1] == _SPACE else low
            if len(low) < max(LEAST, q):
                continue
            last = max(0, len(low) - segment)
            for at in sorted({*range(0, last, segment // 2), last}):
                segs.append(low[at : at + segment])
                owner.append(item)
        self.size = np.array([len(s) for s in segs], np.int64)
        self.item = np.array(owner, np.int64)
        self.edits = np.array([budget(len(s), share, q) for s in segs], np.int64)
        self.least = np.array([max(1, n + 1 - q * (e + 1)) for n, e in zip(self.size, self.edits)], np.int64)
        self.text = np.zeros((len(segs), segment), np.uint32)
        for i, s in enumerate(segs):
            self.text[i, : len(s)] = s
        found = [grams(s, q) for s in segs]
        keys = np.concatenate(found) if segs else np.zeros(0, np.uint64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.first = np.unique(keys[order], return_index=True)
        self.until = np.append(self.first[1:], len(keys))
        self.segment = np.repeat(np.arange(len(segs)), [len(g) for g in found])[order] if segs else keys.astype(np.int64)
        self.place = np.concatenate([np.arange(len(g)) for g in found])[order] if segs else keys.astype(np.int64)
        self.maybe = np.zeros(1 << _BITS, bool)
        self.maybe[(self.keys >> np.uint64(64 - _BITS)).astype(np.int64)] = True

    def candidates(self, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(segment, band) whose shared q-grams reach the segment's bound; a band is named by its first diagonal and has 2 * half of them."""
        none = np.zeros(0, np.int64)
        key = grams(low, self.q)
        if not len(key) or not len(self.keys):
            return none, none
        hit = self.maybe[(key >> np.uint64(64 - _BITS)).astype(np.int64)]
        at = dense(hit, self.text.shape[1] + 2 * self.half, int(self.least.min()))
        where = np.searchsorted(self.keys, key[at])
        where[where == len(self.keys)] = 0
        same = self.keys[where] == key[at]
        at, where = at[same], where[same]
        times = self.until[where] - self.first[where]
        flat = np.repeat(self.first[where] - np.concatenate([[0], np.cumsum(times)[:-1]]), times) + np.arange(times.sum())
        segment, diagonal = self.segment[flat], np.repeat(at, times) - self.place[flat]
        half = self.half
        bands = diagonal // half
        span = 1 << 34
        code = np.concatenate([segment * span + (bands + 8), segment * span + (bands - 1 + 8)])
        code, count = np.unique(code, return_counts=True)
        segment = code // span
        keep = count >= self.least[segment]
        return segment[keep], (code[keep] % span - 8) * half

    def align(self, low: np.ndarray, low_from: np.ndarray, low_to: np.ndarray, segment: np.ndarray, diagonal: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Least edits of each segment against the text places of its band, and where the best one ends; the text is bounded by low_from and low_to."""
        e = int(self.edits.max()) if len(self.edits) else 0
        wide = 2 * self.half + 2 * e + 1
        n = len(segment)
        steps = np.arange(wide)
        cost = np.zeros((n, wide), np.int32)
        best, end = np.full(n, 1 << 20, np.int32), np.zeros(n, np.int64)
        start = diagonal - e
        # free start: any place of the band within the text
        longest = int(self.size[segment].max()) if n else 0
        for i in range(longest):
            at = start[:, None] + i + steps
            inside = (at >= low_from[:, None]) & (at < low_to[:, None])
            there = low[np.clip(at, 0, len(low) - 1)]
            differ = (there != self.text[segment, i][:, None]) | ~inside
            new = cost + differ
            new[:, :-1] = np.minimum(new[:, :-1], cost[:, 1:] + 1)
            new = np.minimum.accumulate(new - steps, 1) + steps
            live = i < self.size[segment]
            cost = np.where(live[:, None], new, cost)
            done = self.size[segment] == i + 1
            if done.any():
                k = cost[done].argmin(1)
                best[done] = cost[done][np.arange(len(k)), k]
                end[done] = start[done] + i + 1 + k
        return best, end

    def search(self, texts: list[str | None]) -> dict[str, np.ndarray]:
        """Rows (text index, item, start, end, edits) of the aligned segments in texts; places are codepoints of the text."""
        low, ends, places = laid_out(texts)
        segment, diagonal = self.candidates(low)
        parts = []
        for k in range(0, len(segment), 4096):
            s, d = segment[k : k + 4096], diagonal[k : k + 4096]
            middle = np.clip(d + self.half + self.size[s] // 2, 0, max(0, len(low) - 1))
            text = np.searchsorted(ends, middle, side="right") - 1
            edits, end = self.align(low, ends[text], ends[text + 1] - 1, s, d)
            good = edits <= self.edits[s]
            parts.append((text[good], self.item[s[good]], (end - self.size[s] - edits)[good], end[good], edits[good]))
        text, item, start, end, edits = np.unique(np.concatenate([np.stack(p) for p in parts], 1), axis=1) if parts else np.zeros((5, 0), np.int64)
        start, end = np.maximum(start - ends[text], 0), np.minimum(end - ends[text], ends[text + 1] - 1 - ends[text])
        for i, t in enumerate(text):
            at = places[t]
            start[i], end[i] = at[min(start[i], len(at) - 1)], at[max(0, end[i] - 1)] + 1
        return {"text": text, "item_id": item, "start": start, "end": end, "edits": edits}


def blocks(benchmark: DataFrame, chars: int = BLOCK_CHARS) -> Iterator[Index]:
    """Indexes of the benchmark, each over items of about ``chars`` characters at most (a longer item alone)."""
    items, size = [], 0
    for row in benchmark.filter("text is not null").select("item_id", "text").toLocalIterator():
        if items and size + len(row["text"]) > chars:
            yield Index(items)
            items, size = [], 0
        items.append((row["item_id"], row["text"]))
        size += len(row["text"])
    yield Index(items)


def _several(benchmark: DataFrame, chars: int) -> bool:
    return (benchmark.agg(F.sum(F.length("text")).alias("n")).first()["n"] or 0) > chars


def regions(docs: DataFrame, benchmark: DataFrame, *, chars: int = BLOCK_CHARS) -> DataFrame:
    """doc_id, item_id, start, end, edits of every aligned segment."""
    spark, out = docs.sparkSession, None
    docs = docs.select("doc_id", "text")
    if _several(benchmark, chars):
        gate = spark.sparkContext.broadcast(Gate.of(benchmark))

        def possible(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in slices(batches, limit=2_000_000):
                yield part.filter(pa.array(gate.value.open(part.column("text").to_pylist())))

        docs = stored(docs.mapInArrow(possible, docs.schema), "possible")
    for index in blocks(benchmark, chars):
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterable[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for part in slices(batches, limit=2_000_000):
                got = shared.value.search(part.column("text").to_pylist())
                ids = part.column("doc_id").take(pa.array(got["text"]))
                numbers = ("item_id", "start", "end", "edits")
                yield pa.record_batch([ids, *(pa.array(got[n].astype(np.int64)) for n in numbers)], names=["doc_id", *numbers])

        found = docs.mapInArrow(run, "doc_id long, item_id long, start long, end long, edits long")
        out = found if out is None else out.unionByName(found)
    return out


def matches(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """One row per document and leaked item: doc_id, item_id, segments found, first start, last end, least edits."""
    return regions(docs, benchmark, **options).groupBy("doc_id", "item_id").agg(
        F.count(F.lit(1)).alias("segments"), F.min("start").alias("start"), F.max("end").alias("end"), F.min("edits").alias("edits")
    )


def clean(docs: DataFrame, benchmark: DataFrame, *, chars: int = BLOCK_CHARS) -> DataFrame:
    """The rows in which no item is found, with all their columns; each row is judged by itself.

    All blocks follow in one pass; with several of them the gate marks the rows that they look at."""
    spark, names, several = docs.sparkSession, docs.columns, _several(benchmark, chars)
    mark = f"_open_{uuid.uuid4().hex}"
    if several:
        gate = spark.sparkContext.broadcast(Gate.of(benchmark))

        def look(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for part in slices(batches, limit=PASSED):
                yield part.append_column(mark, pa.array(gate.value.open(part.column("text").to_pylist())))

        docs = docs.mapInArrow(look, T.StructType([*docs.schema.fields, T.StructField(mark, T.BooleanType())]))
    for index in blocks(benchmark, chars):
        shared = spark.sparkContext.broadcast(index)

        def run(batches: Iterable[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            for part in slices(batches, limit=PASSED):
                at = np.flatnonzero(part.column(mark).to_numpy(zero_copy_only=False)) if several else np.arange(part.num_rows)
                keep = np.ones(part.num_rows, bool)
                if len(at):
                    keep[at[shared.value.search(part.column("text").take(pa.array(at)).to_pylist())["text"]]] = False
                yield part.filter(pa.array(keep))

        docs = docs.mapInArrow(run, docs.schema)
    return docs.select(*names)
