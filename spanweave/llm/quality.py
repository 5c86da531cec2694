"""Text quality by gradient-boosted trees over document statistics.

Statistics of every whole text are computed once and kept as a narrow table; the trees are
fitted on a bounded sample of labelled documents (``TRAIN_ROWS``, smallest hashes) and walk
the table with numpy. Labels, language, source and doc_id are never inputs.

Defined cases: null text counts as empty; empty texts get a score from their (zero)
statistics; without labelled documents all scores are 0.5; a document labelled more than once
is used once per label row; repeated rows each get their score; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spanweave.llm import boosting
from spanweave.llm.batches import bounded_sample, slices
from spanweave.session import stored

#: Documented bound of the training sample.
TRAIN_ROWS = 40_000
CUTOFF = 0.7

STATISTICS = [
    "log_chars", "log_words", "mean_word", "deviation_word", "upper", "digits", "marks", "symbols", "spaces", "other_bytes", "lines_per_kilobyte",
    "distinct_words", "top_word", "repeated_next", "distinct_lines", "marked_words", "bare_marks", "upper_words", "title_words", "short_words", "ratio_packed",
]

_KIND = np.full(256, 5, np.uint8)
for _k, _chars in enumerate((b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b".,;:!?'\"()-", b"#$%&*+/<=>@[\\]^_`{|}~", b" \t\r\n\x0b\x0c", b"")):
    _KIND[list(_chars)] = _k
_KIND[list(b"abcdefghijklmnopqrstuvwxyz")] = 6


def statistics(text: str | None) -> list[float]:
    """The figures named in ``STATISTICS``; all zero for an empty text."""
    raw = (text or "").encode("utf-8", "replace")
    n = len(raw)
    if not n:
        return [0.0] * len(STATISTICS)
    kinds = np.bincount(_KIND[np.frombuffer(raw, np.uint8)], minlength=7) / n
    words = text.split()
    w = len(words)
    lines = [x for x in text.split("\n") if x]
    out = [np.log1p(n), np.log1p(w), 0.0, 0.0, *kinds[:6], 1000 * len(lines) / n]
    if not w:
        return [float(x) for x in out] + [0.0] * (len(STATISTICS) - len(out))
    sizes = np.fromiter(map(len, words), np.int32, w)
    out[2], out[3] = sizes.mean(), sizes.std()
    counts = Counter(words)
    last = "".join([x[-1] for x in words])
    first = "".join([x[0] for x in words])
    out += [
        len(counts) / w, max(counts.values()) / w, sum(map(str.__eq__, words, words[1:])) / w, len(set(lines)) / max(1, len(lines)),
        sum(map(last.count, ".,;:!?")) / w, sum(map(counts.get, ("|", "-", "*", "=", "#"), (0,) * 5)) / w,
        sum(map(str.isupper, words)) / w, sum(map(str.isupper, first)) / w, float((sizes < 3).mean()), len(zlib.compress(raw, 1)) / n,
    ]
    return [float(x) for x in out]


def with_statistics(docs: DataFrame) -> DataFrame:
    """doc_id and its statistics as an array of doubles."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            figures = np.array([statistics(t) for t in part.column("text").to_pylist()])
            arrays = pa.ListArray.from_arrays(np.arange(0, figures.size + 1, len(STATISTICS), dtype=np.int32), figures.ravel())
            yield pa.record_batch([part.column("doc_id"), arrays], names=["doc_id", "x"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, x array<double>")


def is_held_out(doc_id="doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(4)) == 2


def train(figures: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, **options) -> boosting.Forest:
    """Fits trees on about ``rows`` labelled documents at most, those whose doc_ids have the smallest hashes."""
    known = labels.filter("quality is not null").select("doc_id", F.col("quality").cast("double").alias("y"))
    sample = figures.join(bounded_sample(known, rows, "doc_id"), "doc_id").orderBy("doc_id", "x", "y").select("x", "y").toArrow()
    y = sample.column("y").to_numpy()
    x = np.array(sample.column("x").combine_chunks().flatten()).reshape(len(y), len(STATISTICS)) if len(y) else np.zeros((0, len(STATISTICS)))
    return boosting.fit(x, y, **({"trees": 80, "depth": 4, "rate": 0.15} | options))


def score(docs: DataFrame, labels: DataFrame, *, cutoff: float = CUTOFF, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """doc_id, held_out, score, predicted of each document; held-out documents lend no label."""
    figures = stored(with_statistics(docs), "quality").withColumn("held_out", F.coalesce(is_held_out(), F.lit(False)))
    forest = train(figures.filter(~F.col("held_out")), labels, train_rows)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = np.array(b.column("x").flatten()).reshape(b.num_rows, len(STATISTICS))
            s = forest.score(x)
            yield pa.record_batch([b.column("doc_id"), b.column("held_out"), pa.array(s), pa.array((s >= cutoff).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return figures.mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")
