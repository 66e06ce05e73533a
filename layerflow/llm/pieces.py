"""Encoding and decoding with a byte-fallback BPE piece model, by vectorised merge rounds.

All distinct words of a block lie in one flat array of symbols.  Each round looks up the rank of every
neighbouring pair, takes the best rank of each word (a segmented minimum), merges its leftmost
occurrences at once and compacts the array; words without a known pair leave.  A word here is what no
piece can cross: pieces hold the space mark only at their front, so a mark after other text begins a
new word, and so does a line break, which no piece contains.

Several occurrences in one word are merged in the same round only where that equals one merge at a time:
if the merged piece has no partner that would make a better rank than its own.  Other words merge just
their leftmost occurrence in that round.

Defined results: a null text is an empty one; an empty text has only the end id; decoding drops control
ids, turns byte ids into bytes (an invalid byte becomes U+FFFD) and strips the mark put before the text.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from layerflow.llm import store
from layerflow.llm.flat import runs, trim

MARK = "▁"
NO_RANK = np.int32(2**31 - 1)
UNKNOWN = 1 << 20  # a character without a piece is UNKNOWN + its code point
_SLOW = re.compile(f"{MARK}+[^{MARK}\n]*|\n[^{MARK}\n]*")


@dataclass
class PieceModel:
    pieces: list[bytes]  # what each id stands for; empty for control ids
    kinds: np.ndarray  # 0 text, 1 byte, 2 control or unknown
    first_byte: int
    end_id: int
    chars: np.ndarray  # code points with a piece, sorted
    char_ids: np.ndarray
    keys: np.ndarray  # left id << 32 | right id, sorted
    ranks: np.ndarray  # of keys: smaller merges first
    merged: np.ndarray
    risky: np.ndarray  # of ids: has a partner whose merge would come before its own

    @classmethod
    def load(cls, path: str) -> PieceModel:
        """Reads the vocabulary; whether its words can be treated apart is checked."""
        import sentencepiece

        lib = sentencepiece.SentencePieceProcessor(model_file=path)
        n = lib.get_piece_size()
        kinds = np.array([1 if lib.is_byte(i) else 2 if lib.is_control(i) or lib.is_unknown(i) else 0 for i in range(n)], np.int8)
        text = {lib.id_to_piece(i): i for i in range(n) if not kinds[i]}
        if any(MARK in p.lstrip(MARK) or "\n" in p for p in text):
            raise ValueError("a piece crosses a word boundary")
        order = np.zeros(n, np.int32)
        by_score = sorted(text.values(), key=lambda i: (-lib.get_score(i), i))
        order[by_score] = np.arange(len(by_score), dtype=np.int32)
        pairs = {(text[p[:k]] << 32) | text[p[k:]]: i for p, i in text.items() for k in range(1, len(p)) if p[:k] in text and p[k:] in text}
        keys = np.array(sorted(pairs), np.int64)
        merged = np.array([pairs[k] for k in keys.tolist()], np.int32)
        ranks = order[merged]
        best = np.full(n, NO_RANK)
        for side in (keys >> 32, keys & 0xFFFFFFFF):
            np.minimum.at(best, side, ranks)
        first = int(np.flatnonzero(kinds == 1)[0])
        singles = {ord(p): i for p, i in text.items() if len(p) == 1}
        chars = np.array(sorted(singles), np.int64)
        return cls(
            [" \u2047 ".encode() if lib.is_unknown(i) else b"" if kinds[i] == 2 else bytes([i - first]) if kinds[i] == 1 else lib.id_to_piece(i).replace(MARK, " ").encode() for i in range(n)],
            kinds, first, lib.eos_id(), chars, np.array([singles[c] for c in chars.tolist()], np.int32), keys, ranks, merged, best < order,
        )


class Codec:
    """Encodes and decodes whole texts; keeps the ids of words it has seen, up to ``keep`` words."""

    def __init__(self, model: PieceModel, keep: int = 300_000):
        self.m, self.keep = model, keep
        self.table = np.full(0x110000, -1, np.int32)
        self.table[model.chars] = model.char_ids
        lens = np.array([len(p) for p in model.pieces], np.int64)
        self.piece_len, self.piece_at = lens, np.cumsum(lens) - lens
        self.piece_bytes = np.frombuffer(b"".join(model.pieces), np.uint8)
        self._forget()

    def _forget(self) -> None:
        self.codes: dict[str, int] = {}
        self.ids = np.zeros(0, np.int32)
        self.at = np.zeros(1, np.int64)

    # -- words ---------------------------------------------------------------------------------

    @staticmethod
    def words(text: str) -> list[str]:
        """Words without the mark before each; words after a line break begin with it and have no mark."""
        if not text:
            return []
        text = text.replace(MARK, " ")
        if "  " not in text and text[0] != " ":
            return (text.replace("\n", " \n") if "\n" in text else text).split(" ")
        return [w if w[0] == "\n" else w[1:] for w in _SLOW.findall(MARK + text.replace(" ", MARK))]

    def lookup(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """Places of pairs in the model's table; -1 for a pair that doesn't merge."""
        key = (left.astype(np.int64) << 32) | right
        at = np.searchsorted(self.m.keys, key)
        at[at == len(self.m.keys)] = 0
        return np.where(self.m.keys[at] == key, at, -1)

    def merge(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the words, and where each word's begin (and an end)."""
        segments = [w if w[:1] == "\n" else MARK + w for w in words]
        lens = np.array([len(s) for s in segments], np.int64)
        points = np.frombuffer("".join(segments).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64)
        sym = self.table[points].astype(np.int64)
        sym = np.where(sym < 0, points + UNKNOWN, sym)
        word = np.repeat(np.arange(len(words), dtype=np.int64), lens)
        done_sym, done_word = [], []
        pair = np.full(len(sym), -1, np.int64)
        if len(sym) > 1:
            pair[:-1] = np.where(word[:-1] == word[1:], self.lookup(sym[:-1], sym[1:]), -1)
        m = self.m
        while len(sym):
            rank = np.where(pair >= 0, m.ranks[pair], NO_RANK)
            starts = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            size = np.diff(np.concatenate([starts, [len(sym)]]))
            least = np.minimum.reduceat(rank, starts)
            over = least == NO_RANK
            if over.any():  # these words are ready
                out = np.repeat(over, size)
                done_sym.append(sym[out])
                done_word.append(word[out])
                stay = ~out
                sym, word, pair, rank = sym[stay], word[stay], pair[stay], rank[stay]
                if not len(sym):
                    break
                size, least = size[~over], least[~over]
            hit = rank == np.repeat(least, size)
            # of overlapping occurrences every second one, from the left
            begin = np.zeros(len(hit), np.int64)
            a = runs(hit)[0]
            begin[a] = a
            step = np.arange(len(hit)) - np.maximum.accumulate(begin)
            hit &= (step & 1) == 0
            at = np.flatnonzero(hit)
            new = m.merged[pair[at]]
            if m.risky[new].any():  # one merge at a time in these words
                first = np.concatenate([[True], word[at[1:]] != word[at[:-1]]])
                ok = first | ~m.risky[new]
                at, new = at[ok], new[ok]
            sym[at] = new
            live = np.ones(len(sym), bool)
            live[at + 1] = False
            place = np.cumsum(live) - 1
            sym, word, pair = sym[live], word[live], pair[live]
            here = place[at]
            near = np.unique(np.concatenate([here, here[here > 0] - 1]))
            pair[near] = -1
            near = near[near + 1 < len(sym)]
            near = near[word[near] == word[near + 1]]
            pair[near] = self.lookup(sym[near], sym[near + 1])
        sym, word = np.concatenate([*done_sym, np.zeros(0, np.int64)]), np.concatenate([*done_word, np.zeros(0, np.int64)])
        order = np.argsort(word, kind="stable")
        sym, word = sym[order], word[order]
        odd = np.flatnonzero(sym >= UNKNOWN)
        count = np.ones(len(sym), np.int64)
        if len(odd):
            raw = [chr(c).encode("utf-8", "replace") for c in (sym[odd] - UNKNOWN).tolist()]
            count[odd] = [len(r) for r in raw]
            sym, word = np.repeat(sym, count), np.repeat(word, count)
            where = np.repeat((np.cumsum(count) - count)[odd], count[odd]) + np.concatenate([np.arange(len(r)) for r in raw])
            sym[where] = np.frombuffer(b"".join(raw), np.uint8).astype(np.int64) + m.first_byte
        return sym.astype(np.int32), np.searchsorted(word, np.arange(len(words) + 1))

    # -- texts ---------------------------------------------------------------------------------

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Flat ids of the texts, each closed by the end id, and where each text's begin."""
        split = [self.words(t or "") for t in texts]
        if len(self.codes) > self.keep:
            self._forget()
        codes = self.codes
        new = [w for ws in split for w in set(ws).difference(codes)]
        new = list(dict.fromkeys(new))
        if new:
            ids, at = self.merge(new)
            codes.update(zip(new, range(len(codes), len(codes) + len(new))))
            self.at = np.concatenate([self.at, self.at[-1] + at[1:]])
            self.ids = np.concatenate([self.ids, ids])
        n_words = np.array([len(ws) for ws in split], np.int64)
        code = np.fromiter((codes[w] for ws in split for w in ws), np.int64, int(n_words.sum()))
        size = self.at[code + 1] - self.at[code]
        sizes = np.zeros(len(texts), np.int64)
        np.add.at(sizes, np.repeat(np.arange(len(texts)), n_words), size)
        offsets = np.concatenate([[0], np.cumsum(sizes + 1)])
        out = np.full(int(offsets[-1]), self.m.end_id, np.int32)
        body = np.ones(len(out), bool)
        body[offsets[1:] - 1] = False
        first = np.cumsum(size) - size
        out[body] = self.ids[np.arange(int(size.sum())) - np.repeat(first - self.at[code], size)]
        return out, offsets

    def decode(self, ids: np.ndarray, offsets: np.ndarray) -> list[str]:
        """Texts of the ids between consecutive offsets."""
        size = self.piece_len[ids]
        end = np.concatenate([[0], np.cumsum(size)])
        flat = self.piece_bytes[np.arange(int(end[-1])) - np.repeat(end[:-1] - self.piece_at[ids], size)].tobytes()
        out = []
        for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist()):
            raw = flat[end[a] : end[b]]
            k = next((k for k in range(a, b) if self.m.kinds[ids[k]] != 2), -1)
            if k >= 0 and self.m.kinds[ids[k]] == 0 and raw[:1] == b" ":
                raw = raw[1:]
            try:
                out.append(raw.decode())
            except UnicodeDecodeError:
                out.append(_patched(raw))
        return out


def _patched(raw: bytes) -> str:
    """UTF-8 in which each byte that fits no character becomes U+FFFD."""
    out, i = [], 0
    while i < len(raw):
        for n in (1, 2, 3, 4):
            try:
                out.append(raw[i : i + n].decode())
                i += n
                break
            except UnicodeDecodeError:
                continue
        else:
            out.append("�")
            i += 1
    return "".join(out)


def text_blocks(column: pa.Array, limit: int = 1 << 19) -> Iterator[list[str | None]]:
    """Texts of a column in lists of about ``limit`` characters."""
    out, n = [], 0
    for x in column.to_pylist():
        out.append(x)
        n += len(x or "")
        if n >= limit:
            yield out
            out, n = [], 0
    if out:
        yield out


def encode_decode(docs: DataFrame, model_path: str, text: str = "text", with_ids: bool = False) -> DataFrame:
    """Adds n_tokens, ids_sha256, decoded_sha256 (and token_ids, decoded if ``with_ids``) to every row.

    The model is read once on the driver and sent to the executors (its size is that of the vocabulary file).
    """
    spark = docs.sparkSession
    store.text_batches(spark)
    model = spark.sparkContext.broadcast(PieceModel.load(model_path))
    added = ["n_tokens", "ids_sha256", "decoded_sha256", *(["token_ids", "decoded"] if with_ids else [])]
    kept = docs.drop(*added)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields), "n_tokens long, ids_sha256 string, decoded_sha256 string", *(["token_ids array<int>, decoded string"] if with_ids else [])])
    names = kept.columns

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = Codec(model.value)
        digits = [str(i) for i in range(len(codec.m.pieces))]
        for batch in batches:
            n, ids_sha, text_sha, all_ids, decoded = [], [], [], [], []
            for texts in text_blocks(batch.column(names.index(text))):
                ids, offsets = codec.encode(texts)
                back = codec.decode(ids, offsets)
                said = [digits[i] for i in ids.tolist()]
                for a, b, t in zip(offsets[:-1].tolist(), offsets[1:].tolist(), back):
                    n.append(b - a)
                    ids_sha.append(hashlib.sha256(" ".join(said[a:b]).encode()).hexdigest())
                    text_sha.append(hashlib.sha256(t.encode()).hexdigest())
                if with_ids:
                    all_ids += [ids[a:b] for a, b in zip(offsets[:-1], offsets[1:])]
                    decoded += back
            more = [pa.array(all_ids, pa.list_(pa.int32())), pa.array(decoded, pa.string())] if with_ids else []
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(n, pa.int64()), pa.array(ids_sha, pa.string()), pa.array(text_sha, pa.string()), *more], names=[*names, *added])
        trim()

    return kept.mapInArrow(work, schema)
