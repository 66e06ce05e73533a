"""N-gram Jaccard join: which texts share at least ``PERCENT`` of their word shingles.

1. Every text becomes a set of shingle hashes, with a bitmap of twice as many bits or more.  Texts of one set are one class.
2. Two sets that are similar share a token among the first ``|x| - ceil(0.8 |x|) + 1`` of each under any common order
   of tokens.  The order is by hash, tokens that many prefixes hold last; so passages that are copied into many texts
   do not bring all of those together.  Classes that share a prefix token form a group; of equal groups one remains.
3. Every member is compared with the likeliest pivot of its first groups, with several in large groups.  Links found so join classes to components.
4. Groups that still hold several components are searched with signature trees (see ``sigtree``), which drop what is too
   unlike or already joined: once for the likeliest pairs of components, then for all that is still open.  Large groups are dealt in pairs of blocks.  Nothing that could be similar is left out.
5. Open pairs are verified on the whole sets.  Pairs of one class stream past its set; classes with many are dealt over
   several tasks.  Components come from contracting the links, all in tables; no list of them reaches the driver.

Defined results: null texts and texts without words have the empty set and link with nothing, so they are their own
components, named by their own id; rows equal in text share a component even if their ids are equal or null; a
component's id is its smallest id that is not null.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import BinaryType, LongType, StructField, StructType

from layerflow.llm import repeats, sigtree, store
from layerflow.llm.flat import LOWER, NOT_SPACE, blocks, grams, mix, trim, words_of

WORDS = 5
PERCENT = 80
#: Bits of a bitmap: the power of two from twice the set's size on, within these bounds.
BITS = (1024, 1 << 20)
#: A token in more prefixes than this, or than 1 / 2**20 of all prefix tokens, is common; so there are at most 2**20 common tokens.
COMMON = 64
COMMON_SHARE = 2**20
BLOCK = 2048
PAIRS_A_TASK = 1024
#: Groups whose pivots a member is compared with before the search, pivots of a large group, and pairs of two components
#: that the first search takes.  They only save work, as the second search leaves nothing out.
GROUPS, PIVOTS, NEAREST = 4, 6, 3


def shingle_sets(column: pa.Array, words: int = WORDS) -> Iterator[tuple[int, np.ndarray]]:
    """(row, sorted distinct shingle hashes) of every text."""
    for a, b, data, offsets in blocks(column):
        _, _, h, first = words_of(LOWER[data], offsets, NOT_SPACE)
        g = grams(h, words)
        for i in range(b - a):
            lo, hi = first[i], first[i + 1]
            if hi - lo >= words:
                yield a + i, np.unique(g[lo : hi - words + 1])
            elif hi > lo:
                yield a + i, mix(grams(h[lo:hi], int(hi - lo)) + np.uint64(hi - lo))
            else:
                yield a + i, np.zeros(0, np.uint64)


def set_key(tokens: np.ndarray) -> tuple[int, int]:
    if not len(tokens):
        return 0, 0
    return tuple(int(mix(tokens ^ np.uint64(c)).sum(dtype=np.uint64).view(np.int64)) for c in (0x1B873593CC9E2D51, 0x7FEB352D846CA68B))


def bitmap(tokens: np.ndarray) -> bytes:
    width = min(max(1 << (2 * len(tokens) - 1).bit_length(), BITS[0]), BITS[1]) if len(tokens) else BITS[0]
    bits = np.zeros(width, bool)
    bits[(tokens & np.uint64(width - 1)).astype(np.int64)] = True
    return np.packbits(bits).tobytes()


def prefix_length(n, percent: int = PERCENT):
    return n - (percent * n + 99) // 100 + 1


def prefix(tokens: np.ndarray, common: np.ndarray, percent: int) -> np.ndarray:
    """The first tokens of a set: by hash, common ones last."""
    size = prefix_length(len(tokens), percent)
    if not len(common):
        return tokens[:size]
    at = np.searchsorted(common, tokens)
    at[at == len(common)] = 0
    late = common[at] == tokens
    rare = tokens[~late]
    return rare[:size] if len(rare) >= size else np.concatenate([rare, tokens[late][: size - len(rare)]])


def _sets_table(keyed: DataFrame, words: int) -> DataFrame:
    """Of every row: its own columns but the text, text digest, set size, set key and bitmap."""
    names = [c for c in keyed.columns if c != "text"]
    added = [StructField("n_shingles", LongType()), StructField("s1", LongType()), StructField("s2", LongType()), StructField("bits", BinaryType())]
    at = keyed.columns.index("text")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, s1, s2, bits = [], [], [], []
            for _, tokens in shingle_sets(batch.column(at), words):
                a, b = set_key(tokens)
                n.append(len(tokens))
                s1.append(a)
                s2.append(b)
                bits.append(bitmap(tokens))
            own = [c for i, c in enumerate(batch.columns) if i != at]
            yield pa.RecordBatch.from_arrays([*own, pa.array(n, pa.int64()), pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array(bits, pa.binary())], names=[*names, "n_shingles", "s1", "s2", "bits"])

    return keyed.mapInArrow(work, StructType([*(f for f in keyed.schema.fields if f.name != "text"), *added]))


def _prefix_tokens(texts: DataFrame, common, words: int, percent: int, with_key: bool) -> DataFrame:
    """Prefix tokens of all texts, of texts that are equal within one partition once."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        late = common.value
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            token, s1, s2, size = [], [], [], []
            for _, tokens in shingle_sets(batch.column(0), words):
                key = set_key(tokens)
                if len(tokens) and key not in seen:
                    seen.add(key)
                    token.append(prefix(tokens, late, percent))
                    size.append(len(token[-1]))
                    s1.append(key[0])
                    s2.append(key[1])
            if token:
                t = pa.array(np.concatenate(token).view(np.int64))
                keys = [pa.array(np.repeat(np.array(s, np.int64), size)) for s in (s1, s2)] if with_key else []
                yield pa.RecordBatch.from_arrays([t, *keys], names=["token", *(["s1", "s2"] if with_key else [])])
        trim()

    return texts.select("text").mapInArrow(work, "token long" + ", s1 long, s2 long" * with_key)


def common_tokens(texts: DataFrame, words: int, percent: int, total: int) -> np.ndarray:
    least = max(COMMON, total // COMMON_SHARE)
    none = texts.sparkSession.sparkContext.broadcast(np.zeros(0, np.uint64))
    rows = _prefix_tokens(texts, none, words, percent, False).groupBy("token").count().where(F.col("count") > least).select("token").toPandas()
    return np.sort(rows["token"].to_numpy(np.int64).view(np.uint64))


def _verified(pairs: DataFrame, keyed: DataFrame, classes: DataFrame, words: int, percent: int) -> DataFrame:
    """Those of the pairs (a1, a2, b1, b2) whose sets are similar."""
    pairs = store.written(pairs, "pairs")
    ends = pairs.select(F.col("a1").alias("s1"), F.col("a2").alias("s2")).union(pairs.select("b1", "b2")).distinct()
    wanted = classes.join(ends, ["s1", "s2"], "left_semi").select("k1", "k2").hint("shuffle_hash")
    texts = keyed.select("k1", "k2", "text").join(wanted, ["k1", "k2"])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[tuple[int, int]] = set()
        for batch in batches:
            s1, s2, raw = [], [], []
            for _, tokens in shingle_sets(batch.column(0), words):
                key = set_key(tokens)
                if key not in seen:
                    seen.add(key)
                    s1.append(key[0])
                    s2.append(key[1])
                    raw.append(tokens.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(s1, pa.int64()), pa.array(s2, pa.int64()), pa.array(raw, pa.binary())], names=["s1", "s2", "tokens"])
        trim()

    # copies in different partitions give the same row again
    sets = store.written(texts.select("text").mapInArrow(read, "s1 long, s2 long, tokens binary"), "sets").dropDuplicates(["s1", "s2"])
    parts = pairs.groupBy("a1", "a2").agg(F.ceil(F.count("*") / PAIRS_A_TASK).cast("int").alias("parts"))
    heads = sets.select(F.col("s1").alias("a1"), F.col("s2").alias("a2"), "tokens").join(parts, ["a1", "a2"])
    heads = heads.select("a1", "a2", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(None).cast("long").alias("b1"), F.lit(None).cast("long").alias("b2"), "tokens")
    tails = pairs.join(parts, ["a1", "a2"]).join(sets.select(F.col("s1").alias("b1"), F.col("s2").alias("b2"), "tokens"), ["b1", "b2"])
    tails = tails.select("a1", "a2", F.pmod(F.xxhash64("b1", "b2"), F.col("parts")).cast("int").alias("part"), "b1", "b2", "tokens")
    stream = heads.unionByName(tails).repartition("a1", "a2", "part").sortWithinPartitions("a1", "a2", "part", F.asc_nulls_first("b1"))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head, head_key = np.zeros(0, np.uint64), None
        for batch in batches:
            out = []
            for a1, a2, _, b1, b2, raw in zip(*(c.to_pylist() for c in batch.columns)):
                tokens = np.frombuffer(raw, np.uint64)
                if b1 is None:
                    head, head_key = tokens, (a1, a2)
                elif head_key == (a1, a2):
                    at = np.searchsorted(head, tokens)
                    at[at == len(head)] = 0
                    both = int((head[at] == tokens).sum())
                    if 100 * both >= percent * (len(head) + len(tokens) - both):
                        out.append((a1, a2, b1, b2))
            cols = list(zip(*out)) if out else [[], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], names=["a1", "a2", "b1", "b2"])
        trim()

    return store.written(stream.mapInArrow(compare, "a1 long, a2 long, b1 long, b2 long"), "links")


def _name(s1: str, s2: str) -> F.Column:
    return F.concat(F.lpad(F.hex(s1), 16, "0"), F.lpad(F.hex(s2), 16, "0"))


def components(links: DataFrame) -> DataFrame:
    """(node, root) of all nodes of the links (a, b), by contraction: every node hooks to its smallest neighbour."""
    edges = store.written(links.select("a", "b").where("a != b").distinct(), "edges")
    labels = None
    while edges.limit(1).count():
        both = edges.select("a", "b").union(edges.select("b", "a"))
        hook = store.written(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("to")), "hooks")
        edges = edges.join(hook.withColumnRenamed("to", "x"), "a").join(hook.select(F.col("a").alias("b"), F.col("to").alias("y")), "b")
        edges = store.written(edges.select(F.col("x").alias("a"), F.col("y").alias("b")).where("a != b").distinct(), "edges")
        if labels is None:
            labels = hook.select(F.col("a").alias("node"), F.col("to").alias("root"))
        else:
            step = hook.select(F.col("a").alias("root"), "to")
            labels = store.written(labels.join(step, "root", "left").select("node", F.coalesce("to", "root").alias("root")), "labels")
    return labels if labels is not None else links.sparkSession.createDataFrame([], "node string, root string")


def _bounded(pairs: DataFrame, percent: int) -> DataFrame:
    """Of pairs with bitmaps and sizes of both sides: those that may be similar, and how far."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = (batch.column(i).to_pylist() for i in (4, 6))
            nx, ny = (np.asarray(batch.column(i)) for i in (5, 7))
            ok, far = np.zeros(len(nx), bool), np.zeros(len(nx), np.int64)
            widths = np.array([(len(p), len(q)) for p, q in zip(x, y)])
            for p, q in np.unique(widths, axis=0).tolist():
                at = np.flatnonzero((widths == (p, q)).all(axis=1))
                u, v = (sigtree.fold(np.frombuffer(b"".join(z[i] for i in at.tolist()), np.uint64).reshape(-1, w // 8), min(p, q) // 8) for z, w in ((x, p), (y, q)))
                ok[at] = sigtree.pair_bound(u, nx[at], v, ny[at], percent)
                far[at] = np.bitwise_count(u ^ v).sum(axis=1, dtype=np.int64)
            kept = batch.select(["a1", "a2", "b1", "b2", "large"]).filter(pa.array(ok))
            yield pa.RecordBatch.from_arrays([*kept.columns, pa.array(far[ok])], names=["a1", "a2", "b1", "b2", "large", "far"])

    return pairs.select("a1", "a2", "b1", "b2", "bits_a", "n_a", "bits_b", "n_b", "large").mapInArrow(work, "a1 long, a2 long, b1 long, b2 long, large boolean, far long")


def _search_groups(members: DataFrame, percent: int, nearest: int | None = None) -> DataFrame:
    """Open pairs of all groups by signature trees.  members: token, s1, s2, bits, n, root, size (of the group).

    ``nearest``: only so many likeliest pairs between each two components of a group.
    """
    n_blocks = F.ceil(F.col("size") / BLOCK).cast("int")
    dealt = members.withColumn("blocks", n_blocks).withColumn("block", F.pmod(F.xxhash64("s1", "s2"), F.col("blocks")).cast("int"))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("token", F.least("block", "other").alias("p"), F.greatest("block", "other").alias("q"), "block", "s1", "s2", "bits", "n", F.xxhash64("root").alias("root"))
    dealt = dealt.repartition("token", "p", "q").sortWithinPartitions("token", "p", "q")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def search(rows: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
            s1, s2, n, root = (np.asarray(rows.column(i)) for i in (4, 5, 7, 8))
            bits = rows.column(6).to_pylist()
            _, comp = np.unique(root, return_inverse=True)
            cross = rows.column(1)[0].as_py() != rows.column(2)[0].as_py()
            side = np.asarray(rows.column(3)) if cross else None
            pairs = sigtree.pairs_of_any_width(bits, n, comp, side, percent, nearest)
            if nearest:
                pairs = sigtree.nearest_of_components(pairs, comp, nearest)
            swap = (s1[pairs[:, 0]] > s1[pairs[:, 1]]) | ((s1[pairs[:, 0]] == s1[pairs[:, 1]]) & (s2[pairs[:, 0]] > s2[pairs[:, 1]]))
            a, b = np.where(swap, pairs[:, 1], pairs[:, 0]), np.where(swap, pairs[:, 0], pairs[:, 1])
            for at in range(0, len(a), 100_000):
                x, y = a[at : at + 100_000], b[at : at + 100_000]
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in (s1[x], s2[x], s1[y], s2[y])], names=["a1", "a2", "b1", "b2"])

        held = None
        for batch in batches:
            if held is not None:
                batch = pa.concat_batches([held, batch])
            if not batch.num_rows:
                continue
            keys = [np.asarray(batch.column(i)) for i in range(3)]
            change = np.flatnonzero(np.any([k[1:] != k[:-1] for k in keys], axis=0)) + 1
            cut = [0, *change.tolist()]
            for x, y in zip(cut[:-1], cut[1:]):
                yield from search(batch.slice(x, y - x))
            held = batch.slice(cut[-1])
        if held is not None and held.num_rows:
            yield from search(held)
        trim()

    return dealt.mapInArrow(work, "a1 long, a2 long, b1 long, b2 long")


def link_components(docs: DataFrame, key: str = "doc_id", words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """Every row of ``docs`` without its text, with n_shingles, component_id, component and set_id (equal sets have equal ones).

    Columns of these four names are replaced; all others are kept, whatever they are called.
    """
    added = ("n_shingles", "component_id", "component", "set_id")
    names = [c for c in docs.columns if c.lower() not in (*added, "text")]
    docs = docs.select(F.col(key).alias("_key"), "text", F.struct(*names).alias("_row"))
    key = "_key"
    store.text_batches(docs.sparkSession)
    keyed = docs.select("*", *repeats.digest())
    base = store.written(_sets_table(keyed, words), "base")
    classes = base.where("n_shingles > 0").groupBy("s1", "s2").agg(F.min(key).alias("least"), F.min(F.struct("k1", "k2")).alias("t"), F.min("n_shingles").alias("n"), F.min("bits").alias("bits"))
    classes = store.written(classes.select("s1", "s2", "least", "t.*", "n", "bits"), "classes")
    total = classes.agg(F.sum(F.expr(f"n - (({percent} * n + 99) div 100) + 1"))).first()[0] or 0
    spark = docs.sparkSession
    common = spark.sparkContext.broadcast(common_tokens(keyed, words, percent, total))
    rows = _prefix_tokens(keyed, common, words, percent, True).repartition("token").dropDuplicates(["token", "s1", "s2"])
    rows = rows.withColumn("size", F.count("*").over(Window.partitionBy("token"))).where("size > 1")
    rows = store.written(rows, "prefixes")
    # of equal groups one is enough
    named = rows.groupBy("token").agg(F.max("size").alias("size"), F.bit_xor(F.xxhash64("s1", "s2")).alias("x"), F.bit_xor(F.xxhash64("s2", "s1")).alias("y"))
    groups = store.written(named.groupBy("size", "x", "y").agg(F.min("token").alias("token")).select("token"), "groups")
    members = store.written(rows.join(groups, "token"), "members")
    nth = lambda by, order: F.row_number().over(Window.partitionBy(*by).orderBy(*order))
    large = F.col("size") > COMMON
    pivots = members.withColumn("nth", nth(["token"], ["s1", "s2"])).where(F.col("nth") <= PIVOTS).where((F.col("nth") == 1) | large)
    pivots = pivots.select("token", F.col("s1").alias("a1"), F.col("s2").alias("a2"))
    side = lambda x: classes.select(F.col("s1").alias(f"{x}1"), F.col("s2").alias(f"{x}2"), F.col("bits").alias(f"bits_{x}"), F.col("n").alias(f"n_{x}"))
    # a member's first few groups: members of one cluster mostly have the same ones, so the same pivots
    few = members.withColumn("nth", nth(["s1", "s2"], ["token"])).where(F.col("nth") <= GROUPS)
    first = few.select("token", "size", F.col("s1").alias("b1"), F.col("s2").alias("b2")).join(pivots, "token").where("a1 != b1 or a2 != b2")
    first = first.groupBy("a1", "a2", "b1", "b2").agg(F.bool_or(large).alias("large"))
    sizes = lambda x: side(x).drop(f"bits_{x}")
    first = first.join(sizes("a"), ["a1", "a2"]).join(sizes("b"), ["b1", "b2"])
    first = store.written(first.where(100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")).drop("n_a", "n_b"), "pivots")
    first = _bounded(first.join(side("a"), ["a1", "a2"]).join(side("b"), ["b1", "b2"]), percent)
    order = nth(["b1", "b2", "large"], ["far", "a1", "a2"])
    first = first.withColumn("nth", order).where(F.when(F.col("large"), F.col("nth") <= PIVOTS).otherwise(F.col("nth") == 1)).select("a1", "a2", "b1", "b2").distinct()
    links = _verified(first, keyed, classes, words, percent)
    named_links = lambda x: x.select(_name("a1", "a2").alias("a"), _name("b1", "b2").alias("b"))
    roots = components(named_links(links))
    for nearest in (NEAREST, None):  # first what most likely joins components, then whatever is still open
        held = members.select("token", "s1", "s2", "size").withColumn("node", _name("s1", "s2")).join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
        held = store.written(held, "held")
        mixed = held.groupBy("token").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x != y").select("token")
        held = held.join(mixed, "token", "left_semi").join(classes.select("s1", "s2", "bits", "n"), ["s1", "s2"])
        links = links.union(_verified(_search_groups(held, percent, nearest).distinct(), keyed, classes, words, percent))
        roots = components(named_links(links))
    owned = classes.select("s1", "s2", "least", _name("s1", "s2").alias("node")).join(roots, "node", "left").withColumn("root", F.coalesce("root", "node"))
    least = owned.groupBy("root").agg(F.min("least").alias("component_id"))
    owned = owned.join(least, "root").select("s1", "s2", "component_id", F.col("root").alias("component"))
    out = base.join(owned, ["s1", "s2"], "left")
    return out.select("_row.*", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col(key)).alias("component_id"), "component", _name("s1", "s2").alias("set_id"))
