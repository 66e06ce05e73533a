"""Substring deduplication of words with a log-structured fingerprint index.

The index holds fingerprints of word windows: of each segment (see ``repeats``) the hash of its windows' common anchor,
a digest of the whole segment and its place.  It is a list of immutable runs, each sorted by hash within hash
partitions.  A new batch becomes a run of level 0 and is merge-joined with every older run, and with itself, on the hash;
whatever meets is a candidate.  ``FAN_IN`` runs of one level are merged into one of the next (compaction).

Candidates are verified by 128-bit digests of their own words, compared only where the anchors' hashes agree: equal
segments have all their windows repeated; of segments that meet others but equal none, each window is compared with
those of the other candidates.  A repeated window's words go, in all the texts that hold it, old and new; windows are
judged on the input.

What the index holds stands in a manifest in its folder: a numbered file for each state, written whole and then renamed.
``FingerprintIndex(spark, root)`` opens the last one; runs that no manifest names, left by a batch that failed, are
deleted then, and that batch can be added again.  A reader that has opened a manifest reads immutable files, but
compaction deletes runs that the manifest before named: one writer at a time, and no readers during it.

Defined results: null texts have no words; texts with fewer words than a window lose nothing; of copies of a longer text
all words go; kept words are joined by one space.  Other columns stay as they are; those named like a result are
replaced by it.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StringType, StructField

from layerflow.llm import repeats, store
from layerflow.llm.flat import NOT_SPACE, blocks, grams, word_hashes, word_spans

WIDTH = 35
K = 5
FAN_IN = 2
BATCHES = 3


def word_units(data: np.ndarray, offsets: np.ndarray):
    starts, ends = word_spans(data, offsets, NOT_SPACE)
    raw = data.tobytes()
    joined = b" ".join([raw[a:b] for a, b in zip(starts.tolist(), ends.tolist())])
    place = np.concatenate([[0], np.cumsum(ends - starts + 1)])  # a run of words takes its last space along
    return repeats.Slices(joined + b" ", place), grams(word_hashes(data, starts, ends), K), np.searchsorted(starts, offsets)


class FingerprintIndex:
    """Runs of fingerprints under ``root``, a folder that all executors share and that outlives the session."""

    def __init__(self, spark: SparkSession, root: str, width: int = WIDTH):
        self.spark, self.root = spark, root
        self.state = {"version": 0, "width": width, "next": 0, "runs": [], "met": []}
        states = [n for n in store.names(spark, root) if n.startswith("manifest-") and not n.endswith(".new")]
        if states:
            self.state = json.loads(store.read_text(spark, f"{root}/{max(states, key=lambda n: int(n.split('-')[1]))}"))
            if self.state["width"] != width:
                raise ValueError(f"the index holds windows of {self.state['width']} words")
        known = {name for _, name in self.state["runs"]} | set(self.state["met"]) | set(states[-1:])
        for name in store.names(spark, root):
            if name not in known and not name.startswith("manifest-"):
                store.delete(spark, f"{root}/{name}")

    @property
    def runs(self) -> list[tuple[int, str]]:
        """(level, name), oldest first."""
        return [tuple(r) for r in self.state["runs"]]

    def _commit(self, runs: list[tuple[int, str]], met: list[str]) -> None:
        """Writes the next manifest, then deletes what only the one before names."""
        gone = {n for _, n in self.state["runs"]} - {n for _, n in runs} | set(self.state["met"]) - set(met)
        before = self.state["version"]
        self.state |= {"version": before + 1, "runs": [list(r) for r in runs], "met": met}
        store.write_text(self.spark, f"{self.root}/manifest-{before + 1}", json.dumps(self.state))
        for name in [*gone, *([f"manifest-{before}"] if before else [])]:
            store.delete(self.spark, f"{self.root}/{name}")

    def _name(self, kind: str) -> str:
        self.state["next"] += 1
        return f"{kind}-{self.state['next']}"

    def read(self, name: str) -> DataFrame:
        return self.spark.read.schema(repeats.SEGMENT_SCHEMA).parquet(f"{self.root}/{name}")

    def _write_run(self, rows: DataFrame, level: int) -> tuple[int, str]:
        name = self._name(f"run-{level}")
        rows.repartition("h").sortWithinPartitions("h").write.parquet(f"{self.root}/{name}")
        store.release(self.spark)
        return level, name

    def add(self, texts: DataFrame) -> DataFrame:
        """Adds a batch (k1, k2, text); the hashes of it that meet any fingerprint at another place."""
        older = [n for _, n in self.runs]
        new = self._write_run(repeats.find_segments(texts, word_units, self.state["width"], K), 0)
        fresh = self.read(new[1])
        mine = fresh.select("h").distinct()
        met = repeats.met_hashes(fresh)
        for name in older:
            met = met.union(mine.join(self.read(name).select("h").hint("merge"), "h", "left_semi"))
        out = self._name("met")
        met.distinct().write.parquet(f"{self.root}/{out}")
        self._commit([*self.runs, new], [*self.state["met"], out])
        self._compact()
        return self.spark.read.schema("h long").parquet(f"{self.root}/{out}")

    def _compact(self) -> None:
        level = 0
        while len(full := [n for x, n in self.runs if x == level]) >= FAN_IN:
            merged = self.read(full[0])
            for name in full[1:]:
                merged = merged.unionByName(self.read(name))
            self._commit([*(r for r in self.runs if r[0] != level), self._write_run(merged, level + 1)], self.state["met"])
            level += 1

    def drop(self) -> None:
        store.delete(self.spark, self.root)

    def candidates(self) -> DataFrame:
        """All fingerprints, old and new, whose hash was met."""
        met = self.spark.read.schema("h long").parquet(*[f"{self.root}/{n}" for n in self.state["met"]]).distinct()
        rows = self.read(self.runs[0][1])
        for _, name in self.runs[1:]:
            rows = rows.unionByName(self.read(name))
        return rows.join(met.hint("merge"), "h", "left_semi")


def window_digests(texts: DataFrame, asked: DataFrame, width: int) -> DataFrame:
    """Digests of the windows of the asked segments (h, s, k1, k2, lo, n): h, w, s, at."""
    lists = asked.groupBy("k1", "k2").agg(F.collect_list(F.struct("h", "s", "lo", "n")).alias("asked"))
    joined = texts.select("k1", "k2", "text").join(lists.hint("shuffle_hash"), ["k1", "k2"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            k1, k2 = (batch.column(i).to_pylist() for i in (0, 1))
            wanted = batch.column(3)
            for a, b, data, offsets in blocks(batch.column(2)):
                slices, _, first = word_units(data, offsets)
                for i in range(a, b):
                    if (k1[i], k2[i]) in seen:
                        continue
                    seen.add((k1[i], k2[i]))
                    own = wanted[i].values
                    h, lo, n = (np.asarray(own.field(j)) for j in (0, 2, 3))
                    which = np.repeat(np.arange(len(n)), n)
                    at = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
                    start = lo[which] + at + first[i - a]
                    w = pa.array(slices.digests(start, start + width), pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array(h[which]), w, own.field(1).take(pa.array(which)), pa.array(at)], names=["h", "w", "s", "at"])

    return joined.mapInArrow(work, "h long, w binary, s binary, at long")


def repeated_ranges(keyed: DataFrame, index: FingerprintIndex, copies: DataFrame) -> DataFrame:
    """First window and number of windows of all repeated ranges of the texts: k1, k2, lo, n.

    ``keyed`` holds all the texts that the index does, or those whose ranges are wanted and all texts they meet.
    """
    width = index.state["width"]
    met = store.written(index.candidates(), "met")
    kinds = store.written(repeats.kinds_of_segments(met), "kinds")
    # a segment that is alone with its hash needs no closer look
    digests = store.written(window_digests(keyed, kinds.where("kinds is not null"), width), "windows")
    again = store.written(repeats.repeated(digests, ["h", "w"], ["s", "at"]), "again")
    inside = store.written(repeats.folded(digests.join(again, ["h", "w"], "left_semi").select("h", "s", "at")), "inside")
    store.discard(digests, again)
    return repeats.at_all_places(met, inside, kinds, copies)


def remove_repeats(docs: DataFrame, width: int = WIDTH, batches: int = BATCHES, with_text: bool = False) -> DataFrame:
    """Adds n_words, n_removed and kept_sha256 (and kept) to every row of ``docs`` (with a column text)."""
    spark = docs.sparkSession
    keyed, copies = repeats.with_copies(docs)
    index = FingerprintIndex(spark, store.new_path(spark, "fingerprints"), width)
    for i in range(batches):
        index.add(keyed.where(F.pmod(F.col("k1"), F.lit(batches)) == i).where("text is not null"))
    ranges = repeated_ranges(keyed, index, copies)
    index.drop()
    added = [StructField("n_words", LongType()), StructField("n_removed", LongType()), StructField("kept_sha256", StringType())]

    def values(data: np.ndarray, offsets: np.ndarray, found: list) -> Iterator[tuple]:
        starts, ends = word_spans(data, offsets, NOT_SPACE)
        first = np.searchsorted(starts, offsets)
        raw = data.tobytes()
        for i, r in enumerate(found):
            s, e = starts[first[i] : first[i + 1]], ends[first[i] : first[i + 1]]
            gone = repeats.flags(r, len(s), width) if len(s) >= width else np.zeros(len(s), bool)
            kept = b" ".join([raw[x:y] for x, y in zip(s[~gone].tolist(), e[~gone].tolist())])
            yield (len(s), int(gone.sum()), repeats.sha(kept), kept.decode())

    return repeats.covered(keyed, ranges, [*added, *([StructField("kept", StringType())] if with_text else [])], values)
