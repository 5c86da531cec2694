"""Near-duplicate documents by MinHash signatures joined through inverted lists of their coordinates.

A document is the set of its distinct shingles (``WORDS`` words); two are linked if
100 * |intersection| >= 75 * |union|. Steps:

1. Each whole text becomes a set hash and a signature of ``COORDINATES`` minima. Texts with equal sets
   are one class; only its least doc_id goes on.
2. Each class is posted under its (coordinate, value) pairs. Linked classes agree in at least ``AGREE``
   coordinates but for a chance below 3e-8. So values that no other class has are dropped, a class with
   fewer than ``AGREE`` shared values is done, and of the others only the rarest shared values are
   posted - all but ``AGREE`` - 1 of them (prefix): agreeing classes meet in one of these lists.
3. The lists, read as stars around the class with the most common values, fall into families. In a large family
   every class is compared with the family's hub on full sets, which is linear in its size; classes that the hub does
   not link are open. Small families share blocks, all their classes open; a large family's open classes meet all of
   it in blocks bounded in rows and shingles.
4. A block counts collisions on its inverted lists: of each open class the shortest lists, all but ``AGREE`` - 1, are
   merged (prefix), the long ones are skipped over and looked up for the candidates alone. Pairs above the threshold
   that are not connected yet are confirmed on full sets. A block emits a spanning forest of its links, never pairs;
   no list or family is gathered in one task.
5. Components of the forests give each class, and so each document, its component.

Defined cases: a null or empty text, or one of separators only, has no shingle and is linked with nothing; fewer
than ``WORDS`` words are one shingle. Rows of one doc_id are one document: each row keeps its own n_shingles, what
links with any of its texts is in its component. A null doc_id never names a component: such rows get the component
of an equal text with an id, or null, and have no ``kept``. An empty table gives no rows; extra columns are
ignored, in ``first_of_each`` kept, whatever their names.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.llm.batches import slices
from spanweave.operators.components import connected_components
from spanweave.session import stored

WORDS = 5
PERCENT = 75
COORDINATES = 64
AGREE = 28
#: Classes and shingles of a block side, and the size up to which families share a block.
BLOCK, BLOCK_SHINGLES = 1024, 2_000_000
SMALL = 64
#: List entries that a block merges at a time.
MERGED = 2_000_000
#: Most bits of the map that keeps texts without a family from being shuffled.
FILTER_BITS = 1 << 26

_M1, _M2, _GOLD = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB), np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


@cache
def _byte_tables() -> tuple[np.ndarray, np.ndarray]:
    """A number for each byte (A-Z as a-z), 0 for separators; which bytes separate words."""
    number = mix(np.arange(1, 257, dtype=np.uint64) * _GOLD)
    number[65:91] = number[97:123]
    separator = np.zeros(256, bool)
    separator[[32, *range(9, 14)]] = True
    number[separator] = 0
    return number, separator


@cache
def _powers(n: int) -> np.ndarray:
    return np.cumprod(np.concatenate([[np.uint64(1)], np.full(n - 1, _GOLD, np.uint64)]))


@cache
def _coefficients(k: int) -> np.ndarray:
    return mix(np.arange(1, k + 1, dtype=np.uint64) * _M2) | np.uint64(1)


def shingle_sets(texts: list[str | None], words: int = WORDS) -> list[np.ndarray]:
    """The sorted distinct 64-bit shingle hashes of each text."""
    number, separator = _byte_tables()
    raw = [(t or "").encode("utf-8", "surrogatepass") for t in texts]
    flat = np.frombuffer(b" ".join(raw) + b" ", np.uint8)
    ends = np.cumsum([len(r) + 1 for r in raw])
    inside = ~separator[flat]
    first = np.flatnonzero(inside & ~np.concatenate([[False], inside[:-1]]))
    if not len(first):
        return [np.zeros(0, np.uint64) for _ in texts]
    last = np.flatnonzero(inside & ~np.concatenate([inside[1:], [False]])) + 1
    size = last - first
    power = _powers(1 << max(4, int(size.max()).bit_length()))
    at = np.flatnonzero(inside)
    place = at - np.repeat(first, size)
    word = np.add.reduceat(number[flat[at]] * power[place], np.concatenate([[0], np.cumsum(size)[:-1]]))
    word = mix(word + size.astype(np.uint64))
    bound = np.concatenate([[0], np.searchsorted(first, ends, side="left")])
    out, grown = [], None
    if len(word) >= words:
        grown = np.zeros(len(word) - words + 1, np.uint64)
        for j in range(words):
            grown = grown * _M1 + word[j : len(word) - words + 1 + j]
        grown = mix(grown + np.uint64(words))
    for a, b in zip(bound, bound[1:]):
        if b - a >= words:
            out.append(np.unique(grown[a : b - words + 1]))
        elif b > a:
            h = np.zeros(1, np.uint64)
            for w in word[a:b]:
                h = h * _M1 + w
            out.append(mix(h + np.uint64(b - a)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signatures(sets: list[np.ndarray], coordinates: int = COORDINATES) -> np.ndarray:
    """Minima of each non-empty set under ``coordinates`` permutations, as 32-bit numbers."""
    if not sets:
        return np.zeros((0, coordinates), np.uint32)
    flat, starts = np.concatenate(sets), np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    out = np.empty((len(sets), coordinates), np.uint32)
    for j, c in enumerate(_coefficients(coordinates)):
        out[:, j] = np.minimum.reduceat((flat ^ c) * c >> np.uint64(32), starts)
    return out


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.astype(np.uint64).view(np.int64))


def summarize(docs: DataFrame, words: int = WORDS, coordinates: int = COORDINATES) -> DataFrame:
    """doc_id, n_shingles, a 128-bit set hash (h1, h2) and the signature of each document (null without shingles)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, limit=1_000_000):
            sets = shingle_sets(part.column("text").to_pylist(), words)
            size = np.array([len(s) for s in sets])
            some = np.flatnonzero(size)
            sig = signatures([sets[i] for i in some], coordinates)
            rows: list[bytes | None] = [None] * len(sets)
            for i, s in zip(some, sig):
                rows[i] = s.tobytes()
            h1 = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64)
            h2 = np.array([mix(s).sum(dtype=np.uint64) for s in sets], np.uint64)
            yield pa.record_batch([part.column("doc_id"), pa.array(size), _signed(h1), _signed(h2), pa.array(rows, pa.binary())], names=["doc_id", "n_shingles", "h1", "h2", "sig"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, h1 long, h2 long, sig binary")


def postings(classes: DataFrame, coordinates: int = COORDINATES) -> DataFrame:
    """(token, rep): a row for each coordinate of each class; a token stands for one (coordinate, value) pair."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            sig = np.frombuffer(b"".join(b.column("sig").to_pylist()), np.uint32).reshape(b.num_rows, coordinates)
            token = mix(sig.astype(np.uint64) + (np.arange(1, coordinates + 1, dtype=np.uint64) << np.uint64(32)))
            yield pa.record_batch([_signed(token.ravel()), pa.array(np.repeat(b.column("rep").to_numpy(), coordinates))], names=["token", "rep"])

    return classes.select("rep", "sig").mapInArrow(run, "token long, rep long")


def prefixes(tokens: DataFrame, agree: int = AGREE) -> DataFrame:
    """(token, rep, weight): the rarest shared tokens of each class with at least ``agree`` shared ones, all but agree - 1; weight: how common its tokens are."""
    often = stored(tokens.groupBy("token").agg(F.count(F.lit(1)).alias("n")).filter("n > 1"), "frequencies")
    shared = tokens.join(often, "token")
    own = shared.groupBy("rep").agg(F.sort_array(F.collect_list(F.struct("n", "token"))).alias("own"), F.sum("n").alias("weight"))
    own = own.filter(F.size("own") >= agree)
    return own.select("rep", "weight", F.explode(F.slice("own", 1, F.size("own") - (agree - 1))).alias("t")).select("t.token", "rep", "weight")


def families(prefix: DataFrame, classes: DataFrame) -> DataFrame:
    """(rep, n_shingles, family, hub, size, shingles): classes that meet in lists, transitively; hub: the one with the most common tokens."""
    top = F.max(F.struct("weight", (-F.col("rep")).alias("r"))).alias("top")
    lists = prefix.groupBy("token").agg(top, F.count(F.lit(1)).alias("n")).filter("n > 1")
    hub = stored(lists.select("token", (-F.col("top.r")).alias("hub")), "lists")
    star = prefix.select("token", "rep").join(hub, "token").select(F.col("hub").alias("a"), F.col("rep").alias("b"))
    parts = connected_components(star.filter("a <> b").distinct())
    weight = stored(prefix.groupBy("rep").agg(F.first("weight").alias("weight")), "weights")
    member = parts.join(weight, parts["node"] == weight["rep"]).select("rep", "weight", F.col("component").alias("family"))
    # texts of one doc_id are one document's: their classes have one name
    sizes = classes.groupBy("rep").agg(F.sum("n_shingles").alias("n_shingles"))
    member = stored(member.join(sizes, "rep"), "members")
    tops = member.groupBy("family").agg(top, F.count(F.lit(1)).alias("size"), F.sum("n_shingles").alias("shingles"))
    tops = stored(tops.select("family", (-F.col("top.r")).alias("hub"), "size", "shingles"), "families")
    return stored(member.join(tops, "family").select("rep", "n_shingles", "family", "hub", "size", "shingles"), "members")


def pieces(count: Column, shingles: Column) -> Column:
    """Into how many pieces of bounded rows and shingles something of that size is cut."""
    return F.greatest(F.lit(1), F.ceil(count / BLOCK), F.ceil(shingles / BLOCK_SHINGLES)).cast("int")


def collisions(rows: np.ndarray, columns: np.ndarray, agree: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, column) of signatures that agree in at least ``agree`` coordinates, some rows' at a time in their order."""
    n, width = rows.shape
    place = np.arange(width, dtype=np.uint64) << np.uint64(32)
    posted = (columns.astype(np.uint64) + place).ravel()
    order = np.argsort(posted, kind="stable")
    posted, owner = posted[order], order // width
    wanted = rows.astype(np.uint64) + place
    begin = np.searchsorted(posted, wanted.ravel(), side="left").reshape(n, width)
    length = np.searchsorted(posted, wanted.ravel(), side="right").reshape(n, width) - begin
    # all but the agree - 1 longest lists are merged: who agrees often enough is on one of them
    short = np.argsort(length, axis=1, kind="stable")[:, : width - agree + 1]
    begin, length = np.take_along_axis(begin, short, 1), np.take_along_axis(length, short, 1)
    total = np.cumsum(length.sum(1))
    start = 0
    while start < n:
        before = total[start - 1] if start else 0
        stop = max(start + 1, int(np.searchsorted(total, before + MERGED, side="right")))
        many, first = length[start:stop].ravel(), begin[start:stop].ravel()
        at = np.repeat(first - (np.cumsum(many) - many), many) + np.arange(many.sum())
        row = np.repeat(np.repeat(np.arange(start, stop), length.shape[1]), many)
        pair = np.unique(row * np.int64(len(columns)) + owner[at])
        i, j = pair // len(columns), pair % len(columns)
        same = np.concatenate([(rows[i[k : k + 65536]] == columns[j[k : k + 65536]]).sum(1) for k in range(0, len(i), 65536)] or [i])
        yield i[same >= agree], j[same >= agree]
        start = stop


class Sets:
    """Shingle sets of a block, compared exactly."""

    def __init__(self, sets: list[np.ndarray], percent: int):
        self.sets, self.percent = sets, percent
        self.sizes = np.array([len(s) for s in sets])
        self.begin = np.concatenate([[0], np.cumsum(self.sizes)])
        self.lists = None

    def linked(self, i: int, others: np.ndarray) -> np.ndarray:
        """Which of the others are linked with set i: by one count over inverted lists if they are many."""
        if len(others) <= 12:
            both = np.array([len(np.intersect1d(self.sets[i], self.sets[j], assume_unique=True)) for j in others], np.int64)
        else:
            if self.lists is None:
                values, where = np.unique(np.concatenate(self.sets), return_inverse=True)
                order = np.argsort(where, kind="stable")
                owner = np.repeat(np.arange(len(self.sets)), self.sizes)[order]
                self.lists = where, owner, np.searchsorted(where[order], np.arange(len(values) + 1))
            where, owner, start = self.lists
            mine = where[self.begin[i] : self.begin[i + 1]]
            many = start[mine + 1] - start[mine]
            at = np.repeat(start[mine] - (np.cumsum(many) - many), many) + np.arange(many.sum())
            both = np.bincount(owner[at], minlength=len(self.sets))[others]
        return 100 * both >= self.percent * (self.sizes[others] + self.sizes[i] - both)


def compare(
    ids: np.ndarray, sets: list[np.ndarray], row: np.ndarray, column: np.ndarray, joined: np.ndarray,
    *, agree: int, percent: int, coordinates: int,
) -> list[tuple[int, int]]:
    """Links that span what is linked between the rows and the columns of one block; those ``joined`` are connected already."""
    root = np.arange(len(ids))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    exact, out = Sets(sets, percent), []
    if joined.any():
        root[joined] = np.flatnonzero(joined)[0]
    sig = signatures(sets, coordinates)
    rows, columns = np.flatnonzero(row), np.flatnonzero(column)
    for i, j in collisions(sig[rows], sig[columns], agree):
        i, j = rows[i], columns[j]
        once = (i != j) & ~(row[j] & column[i] & (ids[j] < ids[i]))
        i, j = i[once], j[once]
        for group in np.split(np.arange(len(i)), np.flatnonzero(np.diff(i)) + 1):
            if not len(group):
                continue
            x = int(i[group[0]])
            near = j[group]
            fits = 100 * np.minimum(exact.sizes[near], exact.sizes[x]) >= percent * np.maximum(exact.sizes[near], exact.sizes[x])
            near = np.array([y for y in near[fits] if find(int(y)) != find(x)], np.int64)
            for y in near[exact.linked(x, near)] if len(near) else ():
                a, b = find(x), find(int(y))
                if a != b:
                    root[max(a, b)] = min(a, b)
                    out.append((int(ids[x]), int(ids[y])))
    return out


def _sets(table: pa.Table, words: int) -> list[np.ndarray]:
    texts = table.column("text").to_pylist()
    return [x for k in range(0, len(texts), 64) for x in shingle_sets(texts[k : k + 64], words)]


def stars(texts: DataFrame, member: DataFrame, *, words: int, percent: int) -> DataFrame:
    """(hub, rep): the classes of large families that their hub links. The hub goes to each piece of its family."""
    large = member.filter(F.col("size") > SMALL).withColumn("p", pieces(F.col("size"), F.col("shingles")))
    is_hub = F.col("rep") == F.col("hub")
    own = F.pmod(F.xxhash64("rep"), F.col("p")).cast("int")
    dealt = large.filter(~is_hub).select("rep", "hub", own.alias("c"))
    dealt = dealt.unionByName(large.filter(is_hub).select("rep", "hub", F.explode(F.sequence(F.lit(0), F.col("p") - 1)).alias("c")))

    def run(table: pa.Table) -> pa.Table:
        ids, hub = table.column("rep").to_numpy(), table.column("hub").to_numpy()
        at = np.flatnonzero(ids == hub)
        found = np.zeros(0, np.int64)
        if len(at):
            exact = Sets(_sets(table, words), percent)
            others = np.flatnonzero(ids != hub)
            found = ids[others[exact.linked(int(at[0]), others)]] if len(others) else found
        return pa.table({"hub": pa.array(np.repeat(hub[:1], len(found)), pa.int64()), "rep": pa.array(found, pa.int64())})

    full = dealt.join(texts, F.col("rep") == F.col("doc_id")).drop("doc_id")
    return full.groupBy("hub", "c").applyInArrow(run, "hub long, rep long")


def blocks(member: DataFrame, star: DataFrame) -> DataFrame:
    """Members dealt to blocks (g, i, j): side 1 is a row, 2 a column, 3 both; ``joined``: linked by the hub of the family already.

    Many small families share one block. Of a large one the open classes are rows and all are columns; without open ones there is none."""
    few = member.filter(F.col("size") <= SMALL)
    sums = few.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum("n_shingles"), F.lit(0)).alias("s")).first()
    total = F.lit(max(1, -(-sums["n"] // BLOCK), -(-sums["s"] // BLOCK_SHINGLES)))
    shared = few.select(
        "rep", (-1 - F.pmod(F.xxhash64("family"), total)).alias("g"), F.lit(0).alias("i"), F.lit(0).alias("j"),
        F.lit(3).alias("side"), F.lit(False).alias("joined"),
    )
    linked = star.select(F.col("rep").alias("_r"))
    large = member.filter(F.col("size") > SMALL).join(linked, F.col("rep") == F.col("_r"), "left")
    joined = F.col("_r").isNotNull() | (F.col("rep") == F.col("hub"))
    large = stored(large.withColumn("joined", joined).drop("_r"), "starred")
    open_ = large.filter("not joined")
    rows = open_.groupBy(F.col("family").alias("_f")).agg(F.count(F.lit(1)).alias("n"), F.sum("n_shingles").alias("s"))
    rows = stored(rows.select("_f", pieces(F.col("n"), F.col("s")).alias("pr")), "open")
    left = large.join(rows, F.col("family") == F.col("_f")).withColumn("pc", pieces(F.col("size"), F.col("shingles")))
    i, j = (F.pmod(F.xxhash64("rep", F.lit(k)), F.col(p)).cast("int") for k, p in ((1, "pr"), (2, "pc")))
    every = lambda p: F.explode(F.sequence(F.lit(0), F.col(p) - 1))
    base = left.select("rep", F.col("family").alias("g"), "joined", i.alias("i"), j.alias("j"), "pr", "pc")
    across = base.filter("not joined").select("rep", "g", "i", every("pc").alias("j"), F.lit(1).alias("side"), "joined")
    down = base.select("rep", "g", every("pr").alias("i"), "j", F.lit(2).alias("side"), "joined")
    both = across.unionByName(down).groupBy("rep", "g", "i", "j").agg(F.sum("side").cast("int").alias("side"), F.first("joined").alias("joined"))
    return shared.unionByName(both.select(*shared.columns))


def bit_map(ids: DataFrame, column: str, most_bits: int = FILTER_BITS) -> tuple[np.ndarray, int]:
    """A map of at most ``most_bits`` bits in which the ids' places are set, put together word by word by the executors."""
    bits = min(most_bits, 1 << max(16, (16 * ids.count()).bit_length()))

    def mark(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = mix(b.column(0).to_numpy().view(np.uint64)) % np.uint64(bits)
            word, where = np.unique(at >> np.uint64(6), return_inverse=True)
            value = np.zeros(len(word), np.uint64)
            np.bitwise_or.at(value, where, np.uint64(1) << (at & np.uint64(63)))
            yield pa.record_batch([_signed(word), _signed(value)], names=["word", "value"])

    known = ids.select(column).filter(F.col(column).isNotNull())
    rows = known.mapInArrow(mark, "word long, value long").groupBy("word").agg(F.bit_or("value").alias("value")).toArrow()  # bits / 64 rows at most
    table = np.zeros(bits // 64, np.uint64)
    table[rows.column("word").to_numpy()] = rows.column("value").to_numpy().view(np.uint64)
    return table, bits


def maybe_in(docs: DataFrame, ids: DataFrame, column: str, mark: str) -> DataFrame:
    """The rows with ``mark``: true for every doc_id among the ids and a few others, null for null; decided where the rows are read."""
    table, bits = bit_map(ids, column)
    shared = docs.sparkSession.sparkContext.broadcast(table)

    @F.pandas_udf("boolean")
    def look(doc_id: pd.Series) -> pd.Series:
        at = mix(doc_id.to_numpy(np.int64).view(np.uint64)) % np.uint64(bits)
        hit = (shared.value[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1)
        return pd.Series(hit > 0)

    return docs.withColumn(mark, F.when(F.col("doc_id").isNotNull(), look(F.coalesce("doc_id", F.lit(0)))))


def links(docs: DataFrame, member: DataFrame, *, words: int, agree: int, percent: int, coordinates: int) -> DataFrame:
    """(a, b): spanning links between classes, each confirmed on full sets."""
    texts = lambda some: maybe_in(docs.select("doc_id", "text"), some, "rep", "_maybe").filter("_maybe").drop("_maybe")
    star = stored(stars(texts(member.filter(F.col("size") > SMALL)), member, words=words, percent=percent), "stars")
    dealt = stored(blocks(member, star), "blocks")
    full = dealt.join(texts(dealt.select("rep")), F.col("rep") == F.col("doc_id")).drop("doc_id")

    def run(table: pa.Table) -> pa.Table:
        ids, side = table.column("rep").to_numpy(), table.column("side").to_numpy()
        joined = table.column("joined").to_numpy(zero_copy_only=False).astype(bool)
        limits = {"agree": agree, "percent": percent, "coordinates": coordinates}
        out = compare(ids, _sets(table, words), side & 1 > 0, side & 2 > 0, joined, **limits)
        a, b = zip(*out) if out else ((), ())
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    found = full.groupBy("g", "i", "j").applyInArrow(run, "a long, b long")
    return found.unionByName(star.select(F.col("hub").alias("a"), F.col("rep").alias("b")))


KEY = ["n_shingles", "h1", "h2"]


def _grouped(docs: DataFrame, words: int, percent: int, coordinates: int, agree: int) -> tuple[DataFrame, DataFrame]:
    """(summaries, component of each class) of the documents."""
    docs = docs.select("doc_id", "text")
    summary = stored(summarize(docs, words, coordinates), "signatures")
    some = summary.filter("n_shingles > 0")
    least = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "sig")).alias("x")
    classes = stored(some.groupBy(*KEY).agg(least).select(*KEY, F.col("x.doc_id").alias("rep"), "x.sig"), "classes")
    named = classes.filter("rep is not null")
    prefix = stored(prefixes(postings(named, coordinates), agree), "prefixes")
    member = families(prefix, named)
    found = stored(links(docs, member, words=words, agree=agree, percent=percent, coordinates=coordinates), "found")
    parts = connected_components(found)
    merged = classes.join(parts, F.col("rep") == F.col("node"), "left")
    return summary, stored(merged.select(*KEY, F.coalesce("component", "rep").alias("component_id")), "merged")


def find(docs: DataFrame, *, words: int = WORDS, percent: int = PERCENT, coordinates: int = COORDINATES, agree: int = AGREE) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of each document."""
    summary, merged = _grouped(docs, words, percent, coordinates, agree)
    result = summary.filter("n_shingles > 0").join(merged, KEY).select("doc_id", "n_shingles", "component_id")
    alone = summary.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return result.unionByName(alone).withColumn("kept", F.col("doc_id") == F.col("component_id"))


def first_of_each(docs: DataFrame, **options) -> DataFrame:
    """The documents that are the least doc_id of their component (and those without doc_id), with all their columns.

    Of rows with one doc_id and one text one stays. Texts stay where they are read unless their id may be one to drop or
    repeated; only those meet the lists of ids."""
    rows = stored(find(docs, **options), "groups")
    drop = rows.filter("not kept").select(F.col("doc_id").alias("_id")).distinct().withColumn("_drop", F.lit(True))
    again = rows.filter("kept").groupBy(F.col("doc_id").alias("_id")).agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    asked_ids = stored(drop.unionByName(again.select("_id", F.lit(False).alias("_drop"))), "drop")
    mark = f"_maybe_{uuid.uuid4().hex}"
    names = docs.columns
    marked = maybe_in(docs, asked_ids, "_id", mark)
    sure = marked.filter(~F.coalesce(mark, F.lit(False))).select(*names)
    ids = asked_ids.toDF(f"id{mark}", f"drop{mark}")
    asked = marked.filter(mark).join(ids, F.col("doc_id") == F.col(f"id{mark}"), "left").filter(f"not coalesce(drop{mark}, false)")
    once = asked.filter(f"drop{mark} is null").select(*names)
    repeated = asked.filter(f"drop{mark} is not null").select(*names).dropDuplicates(["doc_id", "text"])
    return sure.unionByName(once).unionByName(repeated)
