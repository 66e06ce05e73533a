"""Benchmark decontamination by a prefix-filtered set join.

A benchmark item's windows are its runs of ``WINDOW`` words (a shorter item is one window).  A document holds a window
if all of its word shingles stand in the document in their places, so full containment is asked for, and the necessary
prefix of a window under any fixed order of shingles is one shingle long.  The order is by rarity over all documents:
each window joins by its rarest shingle.  A match gives the window's place in the document (the shingle's place in the
window is known), which has to lie within the document (length and positional bounds); the window's words are then
compared one by one with those around the document's shingle.

Items and documents meet in a join of tables.  What is broadcast is a bitmap of 2 ** ``FILTER_BITS`` hashed shingles, of one
size whatever the number of items: with many items it lets more shingles through to the join, which decides.  A shingle
travels with the words around it that a window could need.

Defined results: null texts and texts without words have no words and no windows; an item without words never occurs;
items of one id unite; the windows of an item with a null id count for n_hit and contaminated, while n_items, items and
items_sha256 leave it out; equal texts have equal results.  Other columns stay as they are; those named like a result are
replaced by it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, BooleanType, LongType, StringType, StructField

from layerflow.llm import repeats, store
from layerflow.llm.flat import ALNUM, LOWER, blocks, grams, trim, words_of

WINDOW = 10
SHINGLE = 3
FILTER_BITS = 24


def item_windows(items: DataFrame, item: str, text: str, window: int) -> DataFrame:
    """(item, window, size, k, grams): the windows of all items; window: its words joined by one space."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, _, data, offsets in blocks(batch.column(1)):
                data = LOWER[data]
                starts, ends, h, first = words_of(data, offsets, ALNUM)
                raw = data.tobytes()
                words = [raw[x:y] for x, y in zip(starts.tolist(), ends.tolist())]
                rows: list[tuple] = []
                for i in range(len(offsets) - 1):
                    lo, hi = int(first[i]), int(first[i + 1])
                    size = min(window, hi - lo)
                    k = min(SHINGLE, size)
                    for j in range(lo, hi - size + 1 if size else lo):
                        rows.append((batch.column(0)[a + i].as_py(), b" ".join(words[j : j + size]).decode(), size, k, grams(h[j : j + size], k).view(np.int64).tolist()))
                cols = list(zip(*rows)) if rows else [[]] * 5
                kinds = [pa.string(), pa.string(), pa.int32(), pa.int32(), pa.list_(pa.int64())]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["item", "window", "size", "k", "grams"])

    rows = items.select(F.col(item).cast("string").alias("i"), F.col(text).alias("t")).where("t is not null")
    return rows.mapInArrow(work, "item string, window string, size int, k int, grams array<long>")


class ShingleFilter:
    """Which shingles may be among those of a set: a bitmap of fixed size over their leading bits, one a length."""

    def __init__(self, shingles: DataFrame, width: int):
        """shingles: (k, gram).  What comes to the driver is at most SHINGLE * 2 ** width bits."""
        self.width = width
        bit = F.shiftrightunsigned("gram", 64 - width)
        rows = shingles.select("k", F.call_function("div", bit, F.lit(32768)).alias("part"), (bit % 32768).alias("bit"))
        self.bits: dict[int, np.ndarray] = {}
        for r in rows.groupBy("k", "part").agg(F.call_function("bitmap_construct_agg", "bit").alias("bits")).collect():
            whole = self.bits.setdefault(r.k, np.zeros(1 << (width - 3), np.uint8))
            whole[r.part * 4096 : (r.part + 1) * 4096] = np.frombuffer(r.bits, np.uint8)

    def at(self, k: int, hashes: np.ndarray) -> np.ndarray:
        bit = hashes >> np.uint64(64 - self.width)
        return np.flatnonzero((self.bits[k][bit >> np.uint64(3)] >> (bit & np.uint64(7)).astype(np.uint8)) & 1)


def _frequencies(docs: DataFrame, text: str, filters) -> DataFrame:
    """(k, gram, n): how often shingles that pass the filter occur in all documents."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = filters.value
        for batch in batches:
            for _, _, data, offsets in blocks(batch.column(0), 1 << 20):
                h = words_of(LOWER[data], offsets, ALNUM)[2]
                for k in f.bits:
                    g = grams(h, k)
                    found, n = np.unique(g[f.at(k, g)], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(found), k, np.int32)), pa.array(found.view(np.int64)), pa.array(n.astype(np.int64))], names=["k", "gram", "n"])

    return docs.select(text).mapInArrow(work, "k int, gram long, n long").groupBy("k", "gram").agg(F.sum("n").alias("n"))


def _places(keyed: DataFrame, filters, window: int) -> DataFrame:
    """(k1, k2, k, gram, place, before, after, around): shingles of the texts that pass the filter.

    around: the words from ``before`` words before the shingle on, as many as a window with it could hold; after: how
    many words of the text follow from the shingle's first one on.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = filters.value
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            keys = list(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
            for a, _, data, offsets in blocks(batch.column(2)):
                data = LOWER[data]
                starts, ends, h, first = words_of(data, offsets, ALNUM)
                raw, rows = data.tobytes(), []
                for k in f.bits:
                    g = grams(h, k)
                    at = f.at(k, g)
                    text = np.searchsorted(first, at, side="right") - 1
                    inside = at + k <= first[text + 1]
                    for p, i, gram in zip(at[inside].tolist(), text[inside].tolist(), g[at[inside]].view(np.int64).tolist()):
                        if keys[a + i] in seen:
                            continue
                        lo, hi = max(int(first[i]), p - window + 1), min(int(first[i + 1]), p + window)
                        around = b" ".join([raw[x:y] for x, y in zip(starts[lo:hi].tolist(), ends[lo:hi].tolist())])
                        rows.append((*keys[a + i], k, gram, p - int(first[i]), p - lo, int(first[i + 1]) - p, around.decode()))
                seen.update(keys[a : a + len(offsets) - 1])
                cols = list(zip(*rows)) if rows else [[]] * 8
                kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds)], names=["k1", "k2", "k", "gram", "place", "before", "after", "around"])
        trim()

    return keyed.select("k1", "k2", "text").mapInArrow(work, "k1 long, k2 long, k int, gram long, place long, before int, after long, around string")


def hits(keyed: DataFrame, windows: DataFrame, window: int, filter_bits: int = FILTER_BITS) -> DataFrame:
    """(k1, k2, window, start, size): every occurrence of a window in a text."""
    sc = keyed.sparkSession.sparkContext
    shingles = store.written(windows.select("window", "size", "k", F.posexplode("grams").alias("off", "gram")).distinct(), "shingles")
    seen = _frequencies(keyed, "text", sc.broadcast(ShingleFilter(shingles.select("k", "gram"), filter_bits)))
    rarest = F.row_number().over(Window.partitionBy("window").orderBy(F.coalesce("n", F.lit(0)), "off"))
    chosen = shingles.join(seen, ["k", "gram"], "left").withColumn("r", rarest).where("r = 1 and n is not null").drop("r", "n")
    chosen = store.written(chosen, "chosen")
    found = _places(keyed, sc.broadcast(ShingleFilter(chosen.select("k", "gram"), filter_bits)), window).join(chosen, ["k", "gram"])
    words = F.slice(F.split("around", " "), F.col("before") - F.col("off") + 1, F.col("size"))
    fits = (F.col("off") <= F.col("before")) & (F.col("size") - F.col("off") <= F.col("after"))
    same = F.when(fits, F.array_join(words, " ") == F.col("window")).otherwise(False)
    return found.where(same).select("k1", "k2", "window", (F.col("place") - F.col("off")).alias("start"), "size").distinct()


def decontaminate(docs: DataFrame, items: DataFrame, text: str = "text", item: str = "item_id", item_text: str = "text", window: int = WINDOW, filter_bits: int = FILTER_BITS) -> DataFrame:
    """Adds n_words, n_hit, n_items, items_sha256, items (sorted ids) and contaminated to every row."""
    keyed, _ = repeats.with_copies(docs, text)
    windows = item_windows(items, item, item_text, window)
    found = store.written(hits(keyed, windows, window, filter_bits), "hits")
    ranges = found.groupBy("k1", "k2").agg(F.sort_array(F.collect_set(F.struct(F.col("start").alias("lo"), F.col("size").cast("int").alias("n")))).alias("ranges"))
    named = found.select("k1", "k2", "window").distinct().join(windows.select("window", "item").where("item is not null").distinct(), "window")
    named = named.groupBy("k1", "k2").agg(F.sort_array(F.collect_set("item")).alias("ids"))
    result = ranges.join(named, ["k1", "k2"], "left")
    added = [StructField(n, LongType()) for n in ("n_words", "n_hit", "n_items")] + [StructField("items_sha256", StringType()), StructField("items", ArrayType(StringType())), StructField("contaminated", BooleanType())]

    def values(data: np.ndarray, offsets: np.ndarray, rows: list) -> Iterator[tuple]:
        first = words_of(LOWER[data], offsets, ALNUM)[3]
        for i, (spans, ids) in enumerate(rows):
            n = int(first[i + 1] - first[i])
            mark = np.zeros(n + 1, np.int64)
            for r in spans or []:
                mark[r["lo"]] += 1
                mark[r["lo"] + r["n"]] -= 1
            n_hit, ids = int((np.cumsum(mark[:-1]) > 0).sum()), ids or []
            yield (n, n_hit, len(ids), hashlib.sha256(",".join(ids).encode()).hexdigest(), ids, n_hit > 0)

    return repeats.with_values(keyed.join(result, ["k1", "k2"], "left").select("row", "ranges", "ids"), text, added, values)
