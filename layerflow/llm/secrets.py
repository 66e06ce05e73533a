"""Secret scans with a trigram inverted index.

Each rule is a regular expression together with a Boolean query over trigrams, derived from the expression's parse:
a literal demands its trigrams, a concatenation the conjunction of its parts' demands, an alternation their disjunction.
An index block holds, for a bounded run of whole texts, the sorted list of texts of each trigram that some rule demands.
Evaluating a query intersects and unites those lists; the regular expression then verifies the candidates.
A rule that demands no trigram scans every text.  Index and texts are ASCII-lower-cased for this, which only adds candidates.

Defined results: a null text is an empty one; matches of one rule are leftmost and don't overlap; places count code
points and ends are exclusive; spans of several kinds may overlap; texts are searched whole.
"""

from __future__ import annotations

import hashlib
import re
import re._constants as sc
import re._parser as sre
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from layerflow.llm import store
from layerflow.llm.flat import LOWER, blocks, trim

ANY = ("any",)  # the query that every text fulfils


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    group: int = 0  # the group that has to be long enough
    least: int = 0


#: The three base rules, in their order, then public formats of well-known credentials.
BASE_RULES = (
    Rule("assign", r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    Rule("access", r"AKIA[A-Z0-9]+", 0, 20),
    Rule("hex", r"[0-9a-f]+", 0, 24),
)
#: A private key from its BEGIN line to the END line that matches it, with no other BEGIN line between.  Where that END is
#: missing, up to the end of the header and base64 lines; line ends may be written out as \\n, lines quoted or indented.
_GAP = r"""(?:\\[nrt]|[\s"'`,>#*|])"""
_KEY = (
    r"-----BEGIN ((?:[A-Z]+ )*)PRIVATE KEY-----"
    r"(?:[^-]*+(?:-(?!----(?:BEGIN |END \1PRIVATE KEY-----))[^-]*+)*+-----END \1PRIVATE KEY-----"
    rf"|(?:{_GAP}*+[A-Z][A-Za-z0-9]*-[A-Za-z]+: [^\r\n\\]*)*"
    rf"(?:(?:{_GAP}++[A-Za-z0-9+/]{{16,}}+={{0,2}}(?={_GAP}|-|\Z))+"
    rf"(?:{_GAP}++(?:(?:[A-Za-z0-9+/]{{4}})*(?:[A-Za-z0-9+/]{{2}}==|[A-Za-z0-9+/]{{3}}=|[A-Za-z0-9+/]{{4}})(?=[\x20\t\r]*(?:\n|\\n|[\"'`]|\Z))|[A-Za-z0-9+/]++=?\Z))?)?)"
)
MORE_RULES = (
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("google", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("stripe", r"[rs]k_live_[A-Za-z0-9]{16,}"),
    Rule("private_key", _KEY),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("url_login", r"[a-z][a-z0-9+]{2,15}://[^\s:/@]{1,64}:[^\s:/@]{3,64}@"),
)


def _trigrams(literal: str) -> tuple:
    found = sorted({literal[i : i + 3] for i in range(len(literal) - 2)})
    return _all([("has", t) for t in found])


def _all(parts: list[tuple]) -> tuple:
    parts = [p for p in dict.fromkeys(parts) if p != ANY]
    return ANY if not parts else parts[0] if len(parts) == 1 else ("and", *parts)


def _some(parts: list[tuple]) -> tuple:
    parts = list(dict.fromkeys(parts))
    return ANY if not parts or ANY in parts else parts[0] if len(parts) == 1 else ("or", *parts)


def trigram_query(pattern: str, exact_limit: int = 16) -> tuple:
    """What trigrams a text must hold, lower-cased, if the pattern matches somewhere in it.

    Walks the parsed pattern; ``exact`` is the set of strings that a part can be, while it is small.
    """

    def ascii_lower(c: int) -> str:
        return chr(c + 32) if 65 <= c <= 90 else chr(c)

    def walk(items) -> tuple[set[str] | None, tuple]:
        queries, run = [], {""}

        def flush():
            nonlocal run
            queries.append(_some([_trigrams(x) for x in sorted(run)]))
            run = {""}

        for op, arg in items:
            exact, query = part(op, arg)
            if exact is not None and len(run) * len(exact) <= exact_limit:
                run = {a + b for a, b in product(run, exact)}
                continue
            flush()
            if exact is not None:
                run = exact if len(exact) <= exact_limit else {""}
                whole = False
            else:
                queries.append(query)
        whole = not queries
        if whole:
            return run, _some([_trigrams(x) for x in sorted(run)])
        flush()
        return None, _all(queries)

    def part(op, arg) -> tuple[set[str] | None, tuple]:
        if op is sc.LITERAL:
            return {ascii_lower(arg)}, ANY
        if op is sc.SUBPATTERN:
            return walk(arg[-1])
        if op is sc.BRANCH:
            sides = [walk(x) for x in arg[1]]
            if all(e is not None for e, _ in sides) and sum(len(e) for e, _ in sides) <= exact_limit:
                return set().union(*(e for e, _ in sides)), ANY
            return None, _some([q for _, q in sides])
        if op in (sc.MAX_REPEAT, sc.MIN_REPEAT):
            low, high, body = arg
            exact, query = walk(body)
            if (low, high) == (0, 1) and exact is not None:
                return exact | {""}, ANY
            return None, query if low else ANY
        if op is sc.IN and all(o is sc.LITERAL for o, _ in arg) and len(arg) <= exact_limit:
            return {ascii_lower(c) for _, c in arg}, ANY
        return None, ANY

    return walk(sre.parse(pattern))[1]


def demanded(query: tuple) -> set[str]:
    return {query[1]} if query[0] == "has" else set().union(set(), *(demanded(q) for q in query[1:])) if query != ANY else set()


class TrigramIndex:
    """Postings of a fixed set of trigrams over a block of texts."""

    def __init__(self, trigrams: list[str]):
        codes = [t.encode() for t in trigrams]
        self.number = {t: i + 1 for i, t in enumerate(trigrams)}
        self.table = np.zeros(1 << 24, np.uint8 if len(trigrams) < 255 else np.uint16)
        for t, c in zip(trigrams, codes):
            if len(c) == 3:
                self.table[c[0] << 16 | c[1] << 8 | c[2]] = self.number[t]
        self.postings: dict[int, np.ndarray] = {}
        self.all = np.zeros(0, np.int64)

    def build(self, data: np.ndarray, offsets: np.ndarray) -> None:
        self.all = np.arange(len(offsets) - 1)
        self.postings = {}
        if len(data) < 3:
            return
        low = LOWER[data].astype(np.int32)
        which = self.table[(low[:-2] << 16) | (low[1:-1] << 8) | low[2:]]
        at = np.flatnonzero(which)
        text = np.searchsorted(offsets, at, side="right") - 1
        inside = at + 2 < offsets[text + 1]
        seen = np.unique(which[at[inside]].astype(np.int64) << 40 | text[inside])
        number, text = seen >> 40, seen & ((1 << 40) - 1)
        cut = np.searchsorted(number, np.arange(1, len(self.number) + 2))
        self.postings = {i + 1: text[cut[i] : cut[i + 1]] for i in range(len(self.number))}

    def find(self, query: tuple) -> np.ndarray:
        if query == ANY:
            return self.all
        if query[0] == "has":
            return self.postings.get(self.number[query[1]], self.all[:0])
        lists = sorted((self.find(q) for q in query[1:]), key=len)
        out = lists[0]
        for x in lists[1:]:
            out = np.intersect1d(out, x, assume_unique=True) if query[0] == "and" else np.union1d(out, x)
        return out


class Scanner:
    def __init__(self, rules: tuple[Rule, ...]):
        self.rules = rules
        self.regexes = [re.compile(r.pattern, re.ASCII) for r in rules]
        self.queries = [trigram_query(r.pattern) for r in rules]
        # a rule with no query scans every text: start it at strings long enough to pass
        wide = {i: re.compile(r.pattern.removesuffix("+") + f"{{{r.least},}}", re.ASCII) for i, r in enumerate(rules) if re.fullmatch(r"\[[^\]]+\]\+", r.pattern) and r.group == 0 and r.least > 1}
        self.regexes = [wide.get(i, x) for i, x in enumerate(self.regexes)]
        self.index = TrigramIndex(sorted(set().union(*(demanded(q) for q in self.queries))))

    def scan(self, texts: list[str | None], data: np.ndarray, offsets: np.ndarray) -> list[list[tuple[int, int, int]]]:
        """Of each text: (start, rule number, end), sorted."""
        found: list[list[tuple[int, int, int]]] = [[] for _ in texts]
        self.index.build(data, offsets)
        for k, (rule, regex, query) in enumerate(zip(self.rules, self.regexes, self.queries)):
            for i in self.index.find(query).tolist():
                for m in regex.finditer(texts[i] or ""):
                    if m.end(rule.group) - m.start(rule.group) >= rule.least:
                        found[i].append((m.start(), k, m.end()))
        for x in found:
            x.sort()
        return found


def scan_secrets(docs: DataFrame, text: str = "text", redact: str | None = None, more: tuple[Rule, ...] = MORE_RULES) -> DataFrame:
    """Adds n_assign, n_access, n_hex, n_secrets, base_sha256 and spans; with ``redact`` also ``redacted``, the text with every found span replaced."""
    rules = BASE_RULES + tuple(more)
    added = ["n_assign", "n_access", "n_hex", "n_secrets", "base_sha256", "spans", *(["redacted"] if redact is not None else [])]
    kept = docs.drop(*added)
    names = kept.columns
    store.text_batches(docs.sparkSession)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields), "n_assign long, n_access long, n_hex long, n_secrets long, base_sha256 string, spans string", *(["redacted string"] if redact is not None else [])])

    def cover(t: str | None, spans: list[tuple[int, int, int]]) -> str | None:
        if not spans:
            return t
        out, at = [], 0
        for a, _, b in spans:
            if b <= at:
                continue
            if a >= at:
                out += [t[at:a], redact]
            at = b
        return "".join([*out, t[at:]])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(rules)
        say = lambda spans: ",".join(f"{rules[k].kind}:{a}:{b}" for a, k, b in spans)
        for batch in batches:
            column = batch.column(names.index(text))
            cols: list[list] = [[] for _ in added]
            for a, b, data, offsets in blocks(column):
                texts = column[a:b].to_pylist()
                for t, spans in zip(texts, scanner.scan(texts, data, offsets)):
                    base = [s for s in spans if s[1] < len(BASE_RULES)]
                    row = [sum(s[1] == k for s in base) for k in range(3)] + [len(spans), hashlib.sha256(say(base).encode()).hexdigest(), say(spans)]
                    for c, v in zip(cols, row + ([cover(t, spans)] if redact is not None else [])):
                        c.append(v)
            kinds = [pa.int64()] * 4 + [pa.string()] * (len(added) - 4)
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(c, k) for c, k in zip(cols, kinds))], names=[*names, *added])
        trim()

    return kept.mapInArrow(work, schema)
