"""Language identification by prediction by partial matching over bytes.

Each language has a variable-order context tree: for every context of up to ``ORDER - 1`` bytes, the counts of
the bytes that followed it in the training texts.  A seen byte costs ``-log2(c / (n + d))`` bits, an unseen one an
escape of ``-log2(d / (n + d))`` bits and then its cost in the next shorter context (n: count of the context,
d: its distinct followers); below order 0 every byte has 1/256.  Statistics are frozen while scoring.

The trees are laid out for numpy: each gram of any language has a number, found from its prefix's number and its
last byte, and a row with every language's exact cost, escapes included; so a text's code length under all
languages is one pass of table look-ups over its bytes.

Training takes rows with text and language that the caller lets it see, ``per_language`` of them a language as
expected number, chosen by a hash of the key: the fit is bounded, the prediction covers every row and whole texts.

Defined results: a text that is null or without any letter is ``und`` with score 0, as is everything when nothing
could be learned.  Ties go to the language first in order.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from layerflow.llm import store
from layerflow.llm.flat import blocks, trim

ORDER = 4
UNDETERMINED = "und"
_LETTER = re.compile(r"[^\W\d_]")


def gram_codes(data: np.ndarray, offsets: np.ndarray, k: int) -> np.ndarray:
    """All k-grams of bytes (k up to 4) within the texts, as numbers."""
    n = len(data) - k + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    code = np.zeros(n, np.uint32)
    for j in range(k):
        code = (code << np.uint32(8)) | data[j : j + n]
    text = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets))
    return code[text[:n] == text[k - 1 :]]


@dataclass
class ContextTrees:
    """Costs of all grams in all languages; number 0 is a gram that no language has."""

    languages: list[str]
    keys: list[np.ndarray]  # of orders 2..: sorted prefix number * 256 + byte of the grams 1..
    cost: list[np.ndarray]  # of orders 1..: float32, gram number x language
    escape: list[np.ndarray]  # of contexts of length 1..: what an unseen byte costs before the shorter context

    @classmethod
    def fit(cls, counts: dict[str, list[tuple[np.ndarray, np.ndarray]]]) -> ContextTrees:
        """counts: for each language and order 1..ORDER, sorted gram codes and how often each occurs."""
        names = sorted(counts)
        keys, cost, escape = [], [], []
        before = np.zeros(0, np.uint32)  # codes of the last order, numbered from 1
        for k in range(ORDER):
            codes = np.arange(256, dtype=np.uint32) if k == 0 else np.unique(np.concatenate([counts[x][k][0] for x in names]))
            rows = np.zeros((len(codes) + (k > 0), len(names)), np.float32)
            context = codes >> np.uint32(8)
            parent = np.searchsorted(before, context) + 1 if k else None  # number of the context in the last order
            if k:
                keys.append(parent.astype(np.int64) * 256 + (codes & np.uint32(255)) if k > 1 else codes.astype(np.int64))
            esc = np.zeros((len(before) + (k > 1), len(names)), np.float32) if k else None
            for j, x in enumerate(names):
                seen, c = counts[x][k]
                if k == 0:
                    n, d = c.sum(), len(seen)
                    rows[:, j] = -np.log2(d / (n + d)) + 8
                    rows[seen, j] = -np.log2(c / (n + d))
                    continue
                at = np.searchsorted(codes, seen)
                owner = (parent[at] - (k == 1)).astype(np.int64)
                n = np.bincount(owner, c, len(esc))
                d = np.bincount(owner, minlength=len(esc))
                known = d > 0
                esc[known, j] = -np.log2(d[known] / (n[known] + d[known]))
                # an unseen byte: escape, then the gram without its first byte in the order below
                short = cls._number(keys[: k - 1], codes & np.uint32((1 << (8 * k)) - 1), k)
                own = esc[(parent - (k == 1)).astype(np.int64), j] + cost[k - 1][short, j]
                own[at] = -np.log2(c / (n[owner] + d[owner]))
                rows[1:, j] = own
            cost.append(rows)
            if k:
                escape.append(esc)
            before = codes
        return cls(names, keys, cost, escape)

    @staticmethod
    def _number(keys: list[np.ndarray], codes: np.ndarray, k: int) -> np.ndarray:
        """Numbers of k-grams given by code, all of which the tables hold."""
        number = ((codes >> np.uint32(8 * (k - 1))) & np.uint32(255)).astype(np.int64)
        for i in range(1, k):
            byte = (codes >> np.uint32(8 * (k - 1 - i))) & np.uint32(255)
            number = np.searchsorted(keys[i - 1], number * 256 + byte) + 1
        return number


#: Entries of a table of four bytes each, of which every worker keeps one an order.
TABLE_ENTRIES = 1 << 26


class _Step:
    """Numbers of grams from their prefixes' numbers and last bytes: 0 for unknown ones.

    A table answers at once where it is small; where it would not be, the sorted keys are searched, with equal results.
    """

    def __init__(self, keys: np.ndarray, prefixes: int):
        self.keys, self.table = keys, None
        if prefixes * 256 <= TABLE_ENTRIES:
            self.table = np.zeros(prefixes * 256, np.int32)
            self.table[keys] = np.arange(1, len(keys) + 1, dtype=np.int32)

    def __call__(self, prefix: np.ndarray, byte: np.ndarray) -> np.ndarray:
        wanted = prefix * np.int64(256) + byte
        if self.table is not None:
            return self.table[wanted]
        at = np.minimum(np.searchsorted(self.keys, wanted), max(0, len(self.keys) - 1))
        return np.where(self.keys[at] == wanted, at + 1, 0).astype(np.int32) if len(self.keys) else np.zeros(len(wanted), np.int32)


class Scorer:
    """Code lengths of texts under all languages."""

    def __init__(self, trees: ContextTrees):
        self.t = trees
        self.step = [_Step(keys, len(trees.cost[k])) for k, keys in enumerate(trees.keys)]  # of orders 2..

    def bits(self, data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        """Text x language: bits to code each text whole, each text with an empty context at its front."""
        t, n = self.t, len(data)
        out = np.zeros((len(offsets) - 1, len(t.languages)))
        if not n:
            return out
        starts = offsets[:-1][np.diff(offsets) > 0]
        # a gram of order k at a place covers the k bytes up to it; none reaches over a text's front
        ids = [data.astype(np.int32)]
        for step in self.step:
            last, now = ids[-1], np.zeros(n, np.int32)
            now[1:] = step(last[:-1], data[1:])
            for j in range(len(ids)):
                near = starts + j
                now[near[near < n]] = 0
            ids.append(now)
        top = len(ids) - 1
        cost = t.cost[top][ids[top]]
        rest = np.flatnonzero(ids[top] == 0)
        for k in range(top, 0, -1):  # no gram of order k+1: escape from its context, if known, to order k
            context = np.zeros(len(rest), np.int32)
            inner = rest > 0
            context[inner] = ids[k - 1][rest[inner] - 1]
            if k == 1:  # order-0 "context" numbers are bytes: real ones are not at a text's front
                front = np.isin(rest, starts, assume_unique=True)
                add = np.where(front[:, None], 0, t.escape[0][context])
            else:
                far = np.zeros(len(rest), bool)
                place = np.searchsorted(starts, rest, side="right") - 1
                far = rest - starts[place] < k
                add = np.where(far[:, None], 0, t.escape[k - 1][np.where(far, 0, context)])
            cost[rest] += add
            found = ids[k - 1][rest] > 0 if k > 1 else np.ones(len(rest), bool)
            cost[rest[found]] += t.cost[k - 1][ids[k - 1][rest[found]]]
            rest = rest[~found]
        full = np.flatnonzero(np.diff(offsets) > 0)
        out[full] = np.add.reduceat(cost, starts, axis=0, dtype=np.float64)
        return out


def train(rows: DataFrame, key: str, text: str, lang: str, per_language: int = 500) -> ContextTrees | None:
    """Trees from rows of the caller's choice with text and language; about ``per_language`` rows each at most."""
    rows = rows.select(F.col(key).alias("k"), F.col(text).alias("t"), F.col(lang).alias("l")).where("t is not null and l is not null")
    sizes = rows.groupBy("l").count()
    part = F.col("count").cast("double")
    u = F.pmod(F.xxhash64(F.col("k").cast("string"), F.lit("fit")), F.lit(1 << 30)) / float(1 << 30)
    picked = rows.join(F.broadcast(sizes), "l").where(u < per_language / part).select("l", "t")

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for name, group in batch.groupby("l"):
                for a, b, data, offsets in blocks(pa.array(group["t"].tolist(), pa.string()), 1 << 23):
                    for k in range(1, ORDER + 1):
                        code, c = np.unique(gram_codes(data, offsets, k), return_counts=True)
                        yield pd.DataFrame({"l": name, "k": k, "code": code.astype(np.int64), "c": c.astype(np.int64)})

    grams = picked.mapInPandas(count, "l string, k int, code long, c long").groupBy("l", "k", "code").agg(F.sum("c").alias("c")).toPandas()
    if not len(grams):
        return None
    grams = grams.sort_values(["l", "k", "code"])
    out = {}
    for name, g in grams.groupby("l"):
        out[name] = [(h["code"].to_numpy(np.uint32), h["c"].to_numpy(np.float64)) for h in (g[g.k == k] for k in range(1, ORDER + 1))]
    return ContextTrees.fit({x: v for x, v in out.items() if len(v[0][0])}) if any(len(v[0][0]) for v in out.values()) else None


def predict(docs: DataFrame, trees: ContextTrees | None, text: str = "text") -> DataFrame:
    """Adds lang_pred, score and bits_per_byte to every row."""
    added = ["lang_pred", "score", "bits_per_byte"]
    kept = docs.drop(*added)
    store.text_batches(docs.sparkSession)
    names, sent = kept.columns, docs.sparkSession.sparkContext.broadcast(trees)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields), "lang_pred string, score double, bits_per_byte double"])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(sent.value) if sent.value is not None else None
        for batch in batches:
            column = batch.column(names.index(text))
            lang, score, rate = [], [], []
            for a, b, data, offsets in blocks(column):
                has = [x is not None and _LETTER.search(x) is not None for x in column[a:b].to_pylist()]
                if scorer is None:
                    lang += [UNDETERMINED] * (b - a)
                    score += [0.0] * (b - a)
                    rate += [None] * (b - a)
                    continue
                bits = scorer.bits(data, offsets)
                best = bits.argmin(axis=1)
                low = bits[np.arange(b - a), best]
                sure = 1 / np.exp2(np.maximum(low[:, None] - bits, -1000)).sum(axis=1)
                size = np.diff(offsets)
                for i in range(b - a):
                    lang.append(scorer.t.languages[best[i]] if has[i] else UNDETERMINED)
                    score.append(float(sure[i]) if has[i] else 0.0)
                    rate.append(float(low[i] / size[i]) if size[i] else None)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(rate, pa.float64())], names=[*names, *added])
        trim()

    return kept.mapInArrow(work, schema)


def fold(key: str | Column) -> Column:
    """crc32 of the key as text, modulo 4; the key's text of a null key is taken as empty."""
    return F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")) % 4


def identify(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", per_language: int = 500) -> DataFrame:
    """Trains on rows of folds other than 2 and predicts every row; adds held_out too."""
    trees = train(docs.where(fold(key) != 2), key, text, lang, per_language)
    return predict(docs.withColumn("held_out", fold(key) == 2), trees, text)
