"""What substring deduplication of words and of bytes have in common.

A window is a run of ``width`` units (words or bytes) of one text.  Its anchor is its leftmost smallest hash of ``k``
consecutive units, so equal windows have equal anchors at the same place within them, and neighbouring windows mostly
share theirs.  A segment is all that consecutive windows with one anchor cover.  Thus a window can only be repeated if
its anchor's hash is, and if two segments are equal, so are all their windows; only segments that differ around an
equal anchor need a closer look.  What is equal is told by 128-bit digests of the words or bytes themselves, and only
among segments whose anchors' hashes agree.

Texts are known by a digest of theirs: equal texts are one text with copies, so repeated rows and null keys do no harm.
A place in the corpus is (digest, place in the text); a hash is repeated if its smallest and its largest place differ,
which partial aggregation finds without gathering anything.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import StructField, StructType

from layerflow.llm import store
from layerflow.llm.flat import blocks, runs, window_minimum

class Slices:
    """The bytes of any run of units of a block: of words, joined by one space, or of bytes themselves."""

    def __init__(self, raw: bytes, place: np.ndarray):
        self.raw, self.place = raw, place  # the place of each unit's first byte, and of an end

    def digests(self, starts: np.ndarray, ends: np.ndarray) -> list[bytes]:
        raw, digest = self.raw, hashlib.blake2b
        return [digest(raw[a:b], digest_size=16).digest() for a, b in zip(self.place[starts].tolist(), self.place[ends].tolist())]


def segments(gram: np.ndarray, width: int, k: int, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first window, windows, anchor) of each segment; ``gram``: a hash of every k units; ``first``: of texts and an end, in units."""
    at = window_minimum(gram, width - k + 1)
    n = len(at)
    valid = np.zeros(n + 1, np.int64)
    a, b = first[:-1], first[1:] - width + 1
    has = (b > a) & (a < n)
    np.add.at(valid, a[has], 1)
    np.add.at(valid, np.minimum(b[has], n), -1)
    ok = np.cumsum(valid[:-1]) > 0
    begin = np.zeros(n, bool)
    if n:
        begin[0] = True
        begin[1:] = at[1:] != at[:-1]
        starts = first[:-1]
        begin[starts[starts < n]] = True
    where = np.flatnonzero(begin)
    end = np.concatenate([where[1:], [n]])
    last = np.cumsum(np.concatenate([[0], ok.astype(np.int64)]))
    size = last[end] - last[where]  # windows of a run that lie within the text: its first ones
    keep = size > 0
    return where[keep], size[keep], at[where[keep]]


def digest(text: str = "text") -> list[F.Column]:
    """A text's digest as two longs; null is not equal to the empty text."""
    d = F.md5(F.concat(F.when(F.col(text).isNull(), F.lit("n")).otherwise(F.lit("t")).cast("binary"), F.coalesce(F.col(text), F.lit("")).cast("binary")))
    return [F.conv(F.substring(d, i, 15), 16, 10).cast("long").alias(k) for i, k in ((1, "k1"), (16, "k2"))]


#: (bytes, offsets) of a block -> (the units' bytes, hashes of every k units, first unit of each text and an end)
Units = Callable[[np.ndarray, np.ndarray], tuple[Slices, np.ndarray, np.ndarray]]

#: ``s`` is a digest of the segment's own words or bytes, ``lo`` its first place in its text, ``more`` its others there
#: (mostly null).
SEGMENT_SCHEMA = "h long, s binary, k1 long, k2 long, lo long, n int, more array<long>"
SEGMENT_NAMES = ["h", "s", "k1", "k2", "lo", "n", "more"]


def find_segments(texts: DataFrame, units: Units, width: int, k: int) -> DataFrame:
    """Segments of all texts (columns k1, k2, text).  Copies within one partition are read once."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            keys = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
            fresh = [i for i, x in enumerate(keys) if x not in seen and not seen.add(x)]
            part = batch.take(pa.array(fresh, pa.int64())) if len(fresh) < len(keys) else batch
            k1, k2 = (np.asarray(part.column(i)) for i in (0, 1))
            for a, b, data, offsets in blocks(part.column(2)):
                slices, gram, first = units(data, offsets)
                where, size, at = segments(gram, width, k, first)
                if not len(where):
                    continue
                s = slices.digests(where, where + size - 1 + width)
                text = np.searchsorted(first, where, side="right") - 1
                lo = where - first[text]
                own, more = _once_a_text(s, text, lo)
                h, *cols = (gram[at].view(np.int64), k1[a + text], k2[a + text], lo, size.astype(np.int32))
                yield pa.RecordBatch.from_arrays([pa.array(h[own]), pa.array([s[i] for i in own.tolist()], pa.binary()), *(pa.array(c[own]) for c in cols), more], names=SEGMENT_NAMES)

    return texts.select("k1", "k2", "text").mapInArrow(work, SEGMENT_SCHEMA)


def _once_a_text(s: list[bytes], text: np.ndarray, lo: np.ndarray) -> tuple[np.ndarray, pa.Array]:
    """Row numbers of each text's distinct segments, and the further places of each."""
    first, second = np.frombuffer(b"".join(s), np.uint64).reshape(-1, 2).T
    order = np.lexsort((lo, second, first, text))
    same = np.ones(len(order), bool)
    for x in (text, first, second):
        same[1:] &= x[order[1:]] == x[order[:-1]]
    same[0] = False
    head = np.flatnonzero(~same)
    if len(head) == len(order):
        return np.arange(len(order)), pa.nulls(len(order), pa.list_(pa.int64()))
    size = np.diff(np.concatenate([head, [len(order)]]))
    places = [lo[order[a + 1 : a + n]] if n > 1 else None for a, n in zip(head.tolist(), size.tolist())]
    return order[head], pa.array(places, pa.list_(pa.int64()))


def met_hashes(found: DataFrame) -> DataFrame:
    """Hashes of segments that stand at more than one place."""
    return repeated(found, ["h"], PLACE, F.col("more").isNotNull())


def repeated(rows: DataFrame, by: list[str], place: list[str], anyway: F.Column | None = None) -> DataFrame:
    """The values of ``by`` that stand at more than one place (or hold ``anyway``)."""
    at = F.xxhash64(*place)
    ends = rows.groupBy(by).agg(F.min(at).alias("_a"), F.max(at).alias("_b"), *([] if anyway is None else [F.bool_or(anyway).alias("_m")]))
    return ends.where("_a != _b" if anyway is None else "_a != _b or _m").select(by)


SEG, PLACE = ["h", "s"], ["k1", "k2", "lo"]


def kinds_of_segments(met: DataFrame) -> DataFrame:
    """Of each distinct segment one place, whether it has others, and, if its hash has several segments, how many."""
    at = F.xxhash64(*PLACE)
    state = met.groupBy(SEG).agg(F.min(F.struct(*PLACE, "n")).alias("_p"), F.min(at).alias("_a"), F.max(at).alias("_b"), F.bool_or(F.col("more").isNotNull()).alias("_m"))
    state = state.select(*SEG, "_p.*", ((F.col("_a") != F.col("_b")) | F.col("_m")).alias("same"))
    kinds = state.groupBy("h").agg(F.count("*").alias("kinds")).where("kinds > 1")
    return state.join(kinds, "h", "left")


def folded(windows: DataFrame) -> DataFrame:
    """Single windows (h, s, at) as ranges of consecutive ones: h, s, at, size."""
    row = F.row_number().over(Window.partitionBy(SEG).orderBy("at"))
    return windows.distinct().withColumn("_g", F.col("at") - row).groupBy(*SEG, "_g").agg(F.min("at").alias("at"), F.count("*").cast("int").alias("size")).drop("_g")


def at_all_places(met: DataFrame, inside: DataFrame, kinds: DataFrame, copies: DataFrame) -> DataFrame:
    """Repeated ranges in texts (k1, k2, lo, n) from those in segments: of repeated segments and of copied texts all."""
    full = kinds.where("same").select(*SEG, F.lit(0).cast("long").alias("at"), F.col("n").alias("size"))
    part = inside.join(kinds.where("not same").select(SEG), SEG, "left_semi")
    everywhere = F.explode(F.concat(F.array("lo"), F.coalesce("more", F.array().cast("array<long>"))))
    ranges = met.select(*SEG, "k1", "k2", everywhere.alias("lo")).join(store.written(part.unionByName(full), "ranges"), SEG)
    ranges = ranges.select("k1", "k2", (F.col("lo") + F.col("at")).alias("lo"), F.col("size").alias("n"))
    return ranges.distinct().union(copies.select("k1", "k2", F.lit(0).cast("long").alias("lo"), F.lit(2**30).alias("n")))


def covered(keyed: DataFrame, ranges: DataFrame, added: list[StructField], values) -> DataFrame:
    """Joins what to remove to every row's text by digest and adds columns, as ``with_values`` does.

    ranges: k1, k2, lo, n (first window and number of windows).
    """
    gathered = ranges.groupBy("k1", "k2").agg(F.sort_array(F.collect_list(F.struct("lo", "n"))).alias("ranges"))
    joined = keyed.join(gathered.hint("shuffle_hash"), ["k1", "k2"], "left").select("row", "ranges")
    return with_values(joined, "text", added, lambda data, offsets, rows: values(data, offsets, [r for (r,) in rows]))


def with_values(joined: DataFrame, text: str, added: list[StructField], values) -> DataFrame:
    """Unpacks ``row`` and adds columns: ``values(bytes, offsets, others)`` yields each text's, in order, for a block of
    texts and the other columns of their rows."""
    fields = joined.schema["row"].dataType.fields
    new = {f.name.lower() for f in added}
    kept = [i for i, f in enumerate(fields) if f.name.lower() not in new]
    at = [f.name for f in fields].index(text)
    names = [*(fields[i].name for i in kept), *(f.name for f in added)]
    kinds = [to_arrow_type(f.dataType) for f in added]

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = batch.column(0).flatten()
            others = list(zip(*(c.to_pylist() for c in batch.columns[1:])))
            cols: list[list] = [[] for _ in added]
            for a, b, data, offsets in blocks(own[at]):
                for row in values(data, offsets, others[a:b]):
                    for c, v in zip(cols, row):
                        c.append(v)
            yield pa.RecordBatch.from_arrays([*(own[i] for i in kept), *(pa.array(c, k) for c, k in zip(cols, kinds))], names=names)

    return joined.mapInArrow(work, StructType([*(fields[i] for i in kept), *added]))


def with_copies(docs: DataFrame, text: str = "text") -> tuple[DataFrame, DataFrame]:
    """Rows, packed so that no name of theirs clashes, with their text and its digest; and the digests several rows share."""
    store.text_batches(docs.sparkSession)
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.col(text).alias("text"), *digest(text))
    return keyed, keyed.groupBy("k1", "k2").count().where("count > 1").select("k1", "k2")


def flags(ranges: list[dict] | None, n: int, width: int) -> np.ndarray:
    """Which of n units some window of the ranges covers."""
    mark = np.zeros(n + 1, np.int64)
    if ranges:
        lo = np.array([r["lo"] for r in ranges], np.int64)
        size = np.array([r["n"] for r in ranges], np.int64)
        np.add.at(mark, lo, 1)
        np.add.at(mark, np.minimum(lo + size - 1 + width, n), -1)
    return np.cumsum(mark[:-1]) > 0


def sha(data: bytes) -> str:
    return hashlib.sha256(data).hexdigest()


def count_runs(removed: np.ndarray) -> int:
    return len(runs(removed)[0])
