"""Substring deduplication of bytes with suffix arrays.

Segments around repeated anchors (see ``repeats``) are the only places where a string of ``WIDTH`` bytes can occur twice.
Each distinct segment is kept once; those whose anchor stands in several kinds of segment are dealt by anchor over shards
of bounded size.  A shard's suffix array is built by induced sorting, its permuted common prefixes tell which suffixes
share ``WIDTH`` bytes with a neighbour, and these are the repeated strings: strings that could be equal have the same
anchor and so the same shard.  A segment that itself stands at several places is repeated throughout.

An anchor whose segments are over ``HOT_BYTES`` long together (a passage within thousands of different texts) is widened:
its strings are halved by how far before the anchor they begin, all strings of a half share a longer core around the
anchor, and the pieces are dealt by that.  Equal pieces are kept once again, and halves that are still too large are
halved again, down to single strings.  Every group ends in a suffix array of bounded size.

Defined results: a null text is an empty one; texts shorter than a string lose nothing; of copies of a longer text all
bytes go.  What is left of a text need not be valid UTF-8, so it is kept as bytes.  Other columns stay as they are; those
named like a result are replaced by it.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StringType, StructField

from layerflow.llm import repeats, store
from layerflow.llm.flat import buffers, mix, powers, runs, trim, window_minimum
from layerflow.llm.sais import permuted_prefixes, suffix_array

WIDTH = 400
K = 32
SHARD_BYTES = 2_000_000
HOT_BYTES = 6_000_000


def _grams(data: np.ndarray) -> np.ndarray:
    """A hash of every K bytes, by doubling."""
    gram, span = mix(data.astype(np.uint64) + np.uint64(1)), 1
    while span < K:
        gram = mix(gram[: max(0, len(gram) - span)] * np.uint64(0x9E3779B97F4A7C15) + gram[span:])
        span *= 2
    return gram


def byte_units(data: np.ndarray, offsets: np.ndarray):
    return repeats.Slices(data.tobytes(), np.arange(len(data) + 1)), _grams(data), offsets


def repeated_windows(texts: list[bytes], width: int = WIDTH) -> list[np.ndarray]:
    """Of each text of a shard, the starts of strings that also start elsewhere in the shard."""
    size = np.array([len(x) for x in texts], np.int64)
    start = np.cumsum(size + 1) - size - 1
    t = np.frombuffer(b"\0".join(texts) + b"\0", np.uint8).astype(np.int16) + 1
    t[start + size] = 0  # no byte: ends a text
    sa = suffix_array(t, 257)
    plcp, phi = permuted_prefixes(t, sa)
    room = np.repeat(start + size, size + 1) - np.arange(len(t))
    ok = room >= width
    hit = np.flatnonzero(ok & (phi >= 0) & (plcp >= width))
    hit = hit[ok[phi[hit]]]
    again = np.zeros(len(t), bool)
    again[hit] = True
    again[phi[hit]] = True
    return [np.flatnonzero(again[a : a + n]) for a, n in zip(start.tolist(), size.tolist())]


#: Surroundings of an anchor that ``may_repeat`` looks at.
AROUND = 8


def may_repeat(texts: list[bytes], width: int = WIDTH) -> np.ndarray:
    """Which whole segments of a shard may share a string of ``width`` bytes with another: no others do.

    A string has width - K bytes besides its anchor.  Cut into AROUND steps, they hold the anchor and AROUND - 1 whole steps
    next to it, some before and the rest after it; so segments that share a string share such a surrounding, for one
    of AROUND numbers of steps before the anchor.  Hashes alone decide: equal ones of different bytes only keep too much.
    """
    size = np.array([len(x) for x in texts], np.int64)
    start = np.cumsum(size) - size
    data = np.frombuffer(b"".join(texts), np.uint8)
    spare = width - K
    places = np.lib.stride_tricks.sliding_window_view(_grams(data), spare + 1)[start]
    anchor = start + places.argmin(axis=1)
    n, step = len(data), spare // AROUND
    up = powers(n + 1)
    sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[:n], dtype=np.uint64)])
    found = np.zeros(len(texts), bool)
    for before in range(AROUND):
        a, b = anchor - before * step, anchor + K + (AROUND - 1 - before) * step
        at = np.flatnonzero((a >= start) & (b <= start + size))
        h = mix((sums[b[at]] - sums[a[at]]) * up[n - a[at]])
        _, which, count = np.unique(h, return_inverse=True, return_counts=True)
        found[at[count[which] > 1]] = True
    return found


def _contents(texts: DataFrame, asked: DataFrame, width: int) -> DataFrame:
    """The bytes of the asked segments, each once: h, s, bytes.  asked: h, s, k1, k2, lo, n."""
    lists = asked.groupBy("k1", "k2").agg(F.collect_list(F.struct("h", "s", "lo", "n")).alias("asked"))
    joined = texts.select("k1", "k2", "text").join(lists.hint("shuffle_hash"), ["k1", "k2"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()

        def pack() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(h, pa.int64()), pa.array(s, pa.binary()), pa.array(raw, pa.binary())], names=["h", "s", "bytes"])

        for batch in batches:
            data, offsets = buffers(batch.column(2))
            h, s, raw = [], [], []
            for i, key in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())):
                if key in seen:
                    continue
                seen.add(key)
                for w in batch.column(3)[i].as_py():
                    a = int(offsets[i]) + w["lo"]
                    h.append(w["h"])
                    s.append(w["s"])
                    raw.append(data[a : a + w["n"] - 1 + width].tobytes())
                if len(raw) >= 2000:
                    yield pack()
                    h, s, raw = [], [], []
            if raw:
                yield pack()

    # copies of a text in other partitions answer alike
    return joined.mapInArrow(work, "h long, s binary, bytes binary").groupBy(*repeats.SEG).agg(F.any_value("bytes").alias("bytes"))


def _shard_ranges(pieces: DataFrame, total: int, width: int) -> DataFrame:
    """Repeated ranges by suffix arrays: h, s, at, size.  pieces (g, h, s, off, p, bytes) of one g meet in one shard."""
    shards = max(1, -(-total // SHARD_BYTES))
    sharded = pieces.select("h", "s", "off", "p", "bytes", F.pmod(F.xxhash64("g"), F.lit(shards)).alias("shard"))

    def work(key, rows):
        rows = rows.combine_chunks()
        which, at, size = [], [], []
        sorted_ = np.ones(rows.num_rows, bool)
        whole = np.flatnonzero(np.asarray(rows.column("p")) < 0)
        if len(whole):
            sorted_[whole] = may_repeat(rows.column("bytes").take(pa.array(whole)).to_pylist(), width)
        rows = rows.filter(pa.array(sorted_)).combine_chunks()
        off = rows.column("off").to_pylist()
        for i, starts in enumerate(repeated_windows(rows.column("bytes").to_pylist(), width) if off else []):
            if len(starts):
                flag = np.zeros(int(starts[-1]) + 1, bool)
                flag[starts] = True
                a, b = runs(flag)
                which += [i] * len(a)
                at += (a + off[i]).tolist()
                size += (b - a).tolist()
        trim()
        taken = rows.select(["h", "s"]).take(pa.array(which, pa.int64()))
        return taken.append_column("at", pa.array(at, pa.int64())).append_column("size", pa.array(size, pa.int32()))

    return sharded.groupBy("shard").applyInArrow(work, "h long, s binary, at long, size int")


def _grouped(pieces: DataFrame, hot_bytes: int) -> tuple[DataFrame, DataFrame | None, int]:
    """Pieces of groups that fit a shard, those of larger groups (None: there are none), and the bytes of the former."""
    sizes = pieces.groupBy("g").agg(F.sum(F.length("bytes")).alias("b"))
    found = sizes.agg(F.sum("b").alias("total"), F.sum(F.when(F.col("b") > hot_bytes, F.col("b"))).alias("hot")).first()
    if not found["hot"]:
        return pieces, None, found["total"] or 0
    large = store.written(sizes.where(F.col("b") > hot_bytes).select("g"), "large")
    return pieces.join(large, "g", "left_anti"), pieces.join(large, "g", "left_semi"), found["total"] - found["hot"]


_PIECE = "g long, h long, s binary, off long, p int, a int, b int, d binary, bytes binary"


def _halves(pieces: DataFrame, width: int) -> DataFrame:
    """Each piece's strings in two: those that begin at most half as far before the anchor as they may, and the others.

    The anchor stands at byte p; strings begin at p - b + 1 to p - a.  All that a half's strings share is its core, whose
    hash is the new group; d is a digest of the new piece.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[tuple] = []
            for h, s, off, p, a, b, raw in zip(*(batch.column(i).to_pylist() for i in range(1, 9) if i != 7)):
                if p < 0:
                    p = int(window_minimum(_grams(np.frombuffer(raw[:width], np.uint8)), width - K + 1)[0])
                for x, y in ((a, (a + b) // 2), ((a + b) // 2, b)):
                    lo, hi = max(0, p - y + 1), min(len(raw) - width, p - x)
                    if x < y and lo <= hi:
                        own, core = raw[lo : hi + width], raw[p - x : p - y + 1 + width]
                        g = int.from_bytes(hashlib.blake2b(b"%d %d " % (x, y) + core, digest_size=8).digest(), "little", signed=True)
                        out.append((g, h, s, off + lo, p - lo, x, y, hashlib.blake2b(own, digest_size=16).digest(), own))
            names = [x.split()[0] for x in _PIECE.split(", ")]
            types = [pa.int64(), pa.int64(), pa.binary(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()]
            cols = list(zip(*out)) if out else [[]] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types)], names=names)

    return pieces.mapInArrow(work, _PIECE)


def _inside(contents: DataFrame, width: int, hot_bytes: int = HOT_BYTES) -> DataFrame:
    """Repeated ranges within different segments of one anchor: h, s, at, size."""
    whole = contents.select(F.col("h").alias("g"), "h", "s", F.lit(0).cast("long").alias("off"), F.lit(-1).alias("p"), F.lit(0).alias("a"), F.lit(width - K + 1).alias("b"), F.lit(None).cast("binary").alias("d"), "bytes")
    fit, large, total = _grouped(whole, hot_bytes)
    out = _shard_ranges(fit, total, width)
    while large is not None:
        parts = store.written(_halves(large, width), "pieces")
        place = F.struct("h", "s", "off")
        kinds = parts.groupBy("g", "d").agg(F.min(F.struct("h", "s", "off", "p", "a", "b", "bytes")).alias("x"), F.min(place).alias("_a"), F.max(place).alias("_b"))
        kinds = store.written(kinds.select("g", "d", "x.*", (F.col("_a") != F.col("_b")).alias("same")), "kinds")
        again = parts.join(kinds.where("same").select("g", "d"), ["g", "d"], "left_semi")
        out = out.unionByName(again.select("h", "s", F.col("off").alias("at"), (F.length("bytes") - width + 1).alias("size")))
        open_ = kinds.join(kinds.groupBy("g").agg(F.count("*").alias("n")).where("n > 1").select("g"), "g", "left_semi")
        # halves of one string each can't differ within a group, so this ends
        fit, large, total = _grouped(open_.select(*[x.split()[0] for x in _PIECE.split(", ")]), hot_bytes)
        out = out.unionByName(_shard_ranges(fit, total, width))
    return out


def repeated_ranges(keyed: DataFrame, copies: DataFrame, width: int, hot_bytes: int = HOT_BYTES) -> DataFrame:
    found = store.written(repeats.find_segments(keyed.where("text is not null"), byte_units, width, K), "segments")
    hashes = store.written(repeats.met_hashes(found), "hashes")
    met = store.written(found.join(hashes, "h", "left_semi"), "met")
    store.discard(found, hashes)
    kinds = store.written(repeats.kinds_of_segments(met), "kinds")
    contents = store.written(_contents(keyed, kinds.where("kinds is not null"), width), "contents")
    inside = store.written(_inside(contents, width, hot_bytes), "inside")
    store.discard(contents)
    return repeats.at_all_places(met, inside, kinds, copies)


def remove_repeats(docs: DataFrame, width: int = WIDTH, with_bytes: bool = False, hot_bytes: int = HOT_BYTES) -> DataFrame:
    """Adds n_bytes, n_removed, n_spans and kept_sha256 (and kept) to every row of ``docs`` (with a column text).

    ``n_bytes`` is the text's whole length; ``n_removed`` says how much of it repeats.
    """
    keyed, copies = repeats.with_copies(docs)
    ranges = repeated_ranges(keyed, copies, width, hot_bytes)
    added = [StructField(n, LongType()) for n in ("n_bytes", "n_removed", "n_spans")] + [StructField("kept_sha256", StringType())]

    def values(data: np.ndarray, offsets: np.ndarray, found: list) -> Iterator[tuple]:
        for i, r in enumerate(found):
            own = data[offsets[i] : offsets[i + 1]]
            gone = repeats.flags(r, len(own), width) if len(own) >= width else np.zeros(len(own), bool)
            kept = own[~gone].tobytes()
            yield (len(own), int(gone.sum()), repeats.count_runs(gone), repeats.sha(kept), kept)

    return repeats.covered(keyed, ranges, [*added, *([StructField("kept", BinaryType())] if with_bytes else [])], values)
