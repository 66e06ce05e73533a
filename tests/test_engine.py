"""Worked examples, invariants and the in-memory reference."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from layerflow.catalog import QUERIES
from layerflow.functions.columns import value_columns
from layerflow.operators import aggregate, arrays, errors, layers, orders, progress, sampling, storage, tiers
from layerflow.operators.policies import POLICIES, BucketQueue
from layerflow.operators.positions import running_sum
from layerflow.plans import layerwise, vertexwise
from layerflow.sources.graphs import GRAPHS, Graph, both_ways, clean_edges

SIX = [(0, 3), (2, 3), (4, 3), (0, 1), (4, 1)]
EIGHT = [(0, 1), (0, 2), (0, 5), (1, 2), (1, 3), (2, 0), (2, 5), (3, 3), (3, 4), (4, 5), (4, 6), (5, 2), (5, 6), (6, 0), (6, 5)]


def small(spark, n, edges):
    v = spark.range(n).select(F.col("id").alias("vid"), F.lit("v").alias("kind"))
    h = v.select("vid", F.lit(0).alias("tile"), F.col("vid").alias("c0"))
    return Graph("small", v, spark.createDataFrame(edges, "src long, dst long"), h, 1)


def by_vid(df, col):
    return [r[col] for r in df.orderBy("vid").collect()]


@pytest.mark.parametrize("run", [aggregate.push_aggregate, aggregate.pull_aggregate])
def test_worked_example(spark, run):
    g = small(spark, 6, SIX)
    assert by_vid(run(g.edges, g.features, g.vertices, "sum"), "c0") == [0, 4, 0, 6, 0, 0]
    assert by_vid(run(g.edges, g.features, g.vertices, "mean"), "c0") == [0, 2, 0, 2, 0, 0]
    assert by_vid(run(g.edges, g.features, g.vertices, "max"), "c0") == [0, 4, 0, 4, 0, 0]


def test_worked_example_orders_and_reads(spark):
    g = small(spark, 6, SIX)
    y = orders.order_yield(g.edges, g.vertices)
    assert [r.vid for r in y.orderBy("pos").collect()] == [0, 4, 2, 1, 3, 5]
    original = orders.order_original(g.vertices)
    assert {r.vid: r.span for r in progress.vertex_span(g.edges, original).collect()} == {1: 4, 3: 4}
    assert {r.vid: r.span for r in progress.vertex_span(g.edges, y).collect()} == {1: 1, 3: 2}
    curve = [r.done / orders.UNIT for r in progress.completion_curve(g.edges, original).orderBy("pos").collect()]
    assert np.allclose(curve, [5 / 6, 5 / 6, 7 / 6, 7 / 6, 2, 2])
    assert {r.batch: r.blocks for r in progress.pull_read_blocks(g.edges, 1, 2).collect()} == {1: 2, 3: 3}


def test_eight(spark):
    g = small(spark, 8, EIGHT)
    assert by_vid(aggregate.push_aggregate(g.edges, g.features, g.vertices, "sum"), "c0") == [8, 0, 6, 4, 3, 12, 9, 0]
    assert by_vid(aggregate.push_aggregate(g.edges, g.features, g.vertices, "max"), "c0") == [6, 0, 5, 3, 3, 6, 5, 0]
    y = orders.order_yield(g.edges, g.vertices)
    assert [r.vid for r in y.orderBy("pos").collect()] == [3, 0, 1, 5, 2, 4, 6, 7]
    assert [r.finished for r in progress.finished_per_chunk(g.edges, y, 2).orderBy("chunk").collect()] == [2, 2, 1, 2]
    s = progress.active_series(g.edges, y, 2).orderBy("chunk").collect()
    assert [r.during for r in s] == [5, 4, 3, 2] and [r.after for r in s] == [3, 2, 2, 0]


def test_replay_of_eight(spark):
    g = small(spark, 8, EIGHT)
    expected = {("original", "fewest"): 3, ("original", "lru"): 3, ("yield", "fewest"): 2, ("yield", "lru"): 2}
    for (o, policy), n in expected.items():
        pos = orders.order_original(g.vertices) if o == "original" else orders.order_yield(g.edges, g.vertices)
        r = tiers.replay_tiers(progress.message_trace(g.edges, pos.select("vid", "pos"), 2), 3, policy, key="dst").summary().first()
        assert (r.evictions, r.reloads, r.finished) == (n, n, 7), (o, policy)
        assert r.most_resident <= 3


def test_replay_invariants(spark, sf_dir):
    g = GRAPHS["trade"](spark, sf_dir)
    pos = orders.order_yield(g.edges, g.vertices).select("vid", "pos").cache()
    trace = progress.message_trace(g.edges, pos, 64).cache()
    peak = progress.active_peak(g.edges, pos, 64).first()["peak"]
    assert tiers.replay_tiers(trace, peak, "fewest").summary().first().evictions == 0
    reloads = {}
    for policy in POLICIES:
        r = tiers.replay_tiers(trace, peak // 2, policy).summary().first()
        assert r.evictions == r.reloads and r.most_resident <= peak // 2
        reloads[policy] = r.reloads
    assert reloads["fewest"] <= min(reloads["lru"], reloads["random"])
    assert reloads["farthest"] <= min(reloads.values()) * 1.05


class PlainStore:
    """The rules of the two-tier store, one vertex at a time: what the arrays have to equal."""

    def __init__(self, slots, policy):
        self.slots, self.policy = slots, POLICIES[policy](0)
        self.pending, self.resident, self.parked, self.step = {}, set(), set(), 0

    def chunk(self, rows):
        back = out = done = 0
        for a in range(0, len(rows), self.slots):
            part = rows[a : a + self.slots]
            new = [r[0] for r in part if r[0] not in self.resident]
            over = len(self.resident) + len(new) - self.slots
            if over > 0:
                gone = self.policy.victims(over, {r[0] for r in part})
                self.resident.difference_update(gone)
                self.parked.update(gone)
                out += len(gone)
            back += len(self.parked & set(new))
            self.parked.difference_update(new)
            self.resident.update(new)
            for v, n, d_in, nxt in part:
                left = self.pending[v] = self.pending.get(v, d_in) - n
                if left:
                    self.policy.note(v, left, self.step, nxt)
                else:
                    self.policy.forget(v)
                    self.resident.remove(v)
                    del self.pending[v]
                    done += 1
            self.step += 1
        return back, out, done


@pytest.mark.parametrize("policy", [p for p in POLICIES if p != "random"])
def test_arrays_equal_the_plain_store(policy):
    rng = np.random.default_rng(3)
    for slots in (1, 3, 10, 200):
        src, dst = np.unique(rng.integers(0, 80, (600, 2)), axis=0).T
        d_in = np.bincount(dst, minlength=80)
        fast, plain = tiers.TierStore(slots, policy), PlainStore(slots, policy)
        for c in range(0, 80, 8):
            v, n = np.unique(dst[(src >= c) & (src < c + 8)], return_counts=True)
            nxt = np.array([min([s // 8 for s in src[dst == x] if s >= c + 8], default=2**40) for x in v], np.int64)
            got = fast.chunk(v, n, d_in[v], nxt)
            assert got == plain.chunk(list(zip(v.tolist(), n.tolist(), d_in[v].tolist(), nxt.tolist())))
            assert set(np.flatnonzero(fast.resident).tolist()) == plain.resident and fast.n_parked == len(plain.parked) and fast.n_resident <= slots


@pytest.mark.parametrize("policy", list(POLICIES))
def test_a_chunk_costs_no_look_at_all_residents(policy, monkeypatch):
    """Fronts are as small as they may be for equality, and used up seldom where they are of the usual size."""
    rng = np.random.default_rng(5)
    src, dst = np.unique(rng.integers(0, 4000, (40_000, 2)), axis=0).T
    d_in = np.bincount(dst, minlength=4000)
    looks = []
    refill = tiers.TierStore._refill
    monkeypatch.setattr(tiers.TierStore, "_refill", lambda self, n: (looks.append(n), refill(self, n)))
    found = []
    for front in ((1, 3), (1 << 12, 1 << 17)):
        monkeypatch.setattr(tiers.TierStore, "FRONT", front)
        fast, plain, got = tiers.TierStore(1500, policy), PlainStore(1500, policy), []
        looks.clear()
        for c in range(0, 4000, 16):
            v, n = np.unique(dst[(src >= c) & (src < c + 16)], return_counts=True)
            nxt = np.array([min([s // 16 for s in src[(dst == x) & (src >= c + 16)]], default=2**40) for x in v] if policy == "farthest" else v * 0, np.int64)
            got.append(fast.chunk(v, n, d_in[v], nxt))
            if policy != "random":
                assert got[-1] == plain.chunk(list(zip(v.tolist(), n.tolist(), d_in[v].tolist(), nxt.tolist())))
        found.append(got)
    assert found[0] == found[1] and sum(x[1] for x in found[0]) > 4000 and len(looks) < 30


def test_chunks_copy_no_front(monkeypatch):
    """The front of smallest keys is rebuilt once in many chunks, not in each."""
    copies, insert = [], np.insert
    monkeypatch.setattr(tiers.np, "insert", lambda *a: (copies.append(1), insert(*a))[1])
    rng = np.random.default_rng(6)
    src, dst = np.unique(rng.integers(0, 4000, (40_000, 2)), axis=0).T
    d_in = np.bincount(dst, minlength=4000)
    state, out = tiers.TierStore(1500, "fewest"), 0
    for c in range(0, 4000, 16):
        v, n = np.unique(dst[(src >= c) & (src < c + 16)], return_counts=True)
        out += state.chunk(v, n, d_in[v], v * 0)[1]
    assert out > 4000 and len(copies) < 25


def test_runs_over_batches():
    """Destinations over several batches, one without a position and one without messages."""
    rows = sorted([(1, -1 - 7), (1, 0), (1, 0), (1, 3), (2, 5), (3, -1 - 9), (4, -1 - 8), *((4, c // 2) for c in range(40))])
    batches = [pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows[i : i + 3])], names=["dst", "x"]) for i in range(0, len(rows), 3)]
    got = [tuple(r.values()) for b in progress._runs(iter(batches), 4) for r in b.to_pylist()]
    assert got == [(0, 1, 2, 3, 7, 1, 3), (3, 1, 1, 3, 7, 0, None), *((c, 4, 2, 40, 8, 38 - 2 * c, c + 1 if c < 19 else None) for c in range(20))]
    assert list(progress._runs(iter([]))) == []


def test_edges_both_ways(spark):
    """Repeats, loops, nulls and pairs given in both directions: each edge and its reverse once."""
    e = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (None, 1), (4, None), (5, 4)], "src int, dst int")
    got = both_ways(e)
    assert sorted(map(tuple, got.collect())) == [(1, 2), (2, 1), (3, 3), (4, 5), (5, 4)] and [t for _, t in got.dtypes] == ["bigint", "bigint"]


def test_replay_of_rows_and_of_runs(spark, sf_dir):
    """A trace with and without what the runs add, in blocks of few chunks: equal stores and equal peaks."""
    g = GRAPHS["copurchase"](spark, sf_dir)
    runs = progress.message_runs(g.edges, orders.order_yield(g.edges, g.vertices), 4).cache()
    plain = runs.drop("left", "nxt")
    assert progress.trace_peak(runs) == progress.trace_peak(plain) > 0
    for policy in ("fewest", "farthest"):
        a, b = (tiers.replay_tiers(t, 40, policy, shards=2) for t in (runs, plain))
        assert a.summary().first() == b.summary().first() and a.summary().first().evictions > 0
        assert sorted(map(tuple, a.reloads.collect())) == sorted(map(tuple, b.reloads.collect()))


def test_replay_of_dealt_arrays(spark, sf_dir):
    """Edges and messages dealt as arrays, in many small shares: scores, peaks and stores as of rows; no edges at all."""
    g = GRAPHS["copurchase"](spark, sf_dir)
    plain = orders.order_yield(g.edges, g.vertices).cache()
    assert sorted(orders.order_yield(g.edges, g.vertices, pairs=g.edges.count()).collect()) == sorted(plain.collect())
    assert sorted(orders.dealt_scores(g.edges, g.vertices, 10, "none").collect()) == sorted(orders.yield_scores(g.edges, g.vertices, "none").collect())
    runs = progress.message_runs(g.edges, plain, 4).cache()
    for policy in ("fewest", "farthest"):
        packed = tiers.packed_runs(g.edges, plain, 4, far=policy == "farthest", shards=2)
        assert tiers.packed_peak(packed) == progress.trace_peak(runs) > 0
        a, b = tiers.replay_packed(packed, 40, policy, shards=2), tiers.replay_tiers(runs, 40, policy, shards=2)
        assert a.summary().first() == b.summary().first() and a.summary().first().evictions > 0
        assert sorted(map(tuple, a.reloads.collect())) == sorted(map(tuple, b.reloads.collect()))
    none = tiers.packed_runs(g.edges.limit(0), plain, 4)
    assert tiers.packed_peak(none) == 0 and tiers.replay_packed(none, 1).chunks.count() == 0


def test_pairs_dealt_and_sorted(monkeypatch):
    """Every pair arrives once, all of a key in one part; keys past 31 bits are sorted as well."""
    from layerflow.operators import arrays

    monkeypatch.setattr(arrays, "SHARE", 50)
    rng = np.random.default_rng(9)
    for top in (40, 1 << 40):
        key, value = rng.integers(0, top, 500), rng.integers(-9, 9, 500)
        dealer = arrays.Dealer(3)
        rows = pa.Table.from_batches([*dealer.add(key[:120], value[:120]), *dealer.add(key[120:], value[120:]), *dealer.rest()])
        met = [arrays.sides(rows.filter(pa.array(np.asarray(rows["part"]) == p)).to_batches())[0] for p in range(3)]
        assert sum(len(np.unique(k)) for k, _ in met) == len(np.unique(key))
        pairs = [x for k, v in met for x in zip(*(c.tolist() for c in arrays.sorted_pairs(k, v)))]
        assert sorted(pairs) == sorted(zip(key.tolist(), value.tolist())) and all(list(zip(*arrays.sorted_pairs(k, v))) == sorted(zip(k, v)) for k, v in met)


@pytest.mark.parametrize("policy", list(POLICIES))
def test_full_slices_pass_at_once(policy, monkeypatch):
    """Chunks of many times the slots: the same partial sums as slice by slice, in three slices a chunk at most."""
    rng = np.random.default_rng(8)
    slices, one = [], tiers.PartialSums._slice
    monkeypatch.setattr(tiers.PartialSums, "_slice", lambda self, *a: (slices.append(1), one(self, *a))[1])

    def plain(self, dst, values, local):
        order = np.argsort(dst, kind="stable")
        ids, first = np.unique(dst[order], return_index=True)
        sums, count = np.add.reduceat(values[order], first, axis=0), np.diff(np.append(first, len(dst)))
        for a in range(0, len(ids), self.slots):
            yield from one(self, ids[a : a + self.slots], sums[a : a + self.slots], count[a : a + self.slots], local[order][first[a : a + self.slots]])

    for slots in (1, 5, 7, 40):
        dst = rng.integers(0, 120, 3000)
        values, local = rng.integers(0, 9, (3000, 2)), np.bincount(dst, minlength=120)[dst]
        fast, slow, found = tiers.PartialSums(slots, policy, 2), tiers.PartialSums(slots, policy, 2), ([], [])
        slices.clear()
        for a in range(0, 3000, 150):
            for store, add, rows in ((fast, fast.add, found[0]), (slow, lambda *x: plain(slow, *x), found[1])):
                for v, n, x in add(dst[a : a + 150], values[a : a + 150], local[a : a + 150]):
                    rows.extend((a, *r) for r in zip(v.tolist(), n.tolist(), map(tuple, x.tolist())))
            assert len(fast.ids) <= slots and fast.ids.tolist() == slow.ids.tolist() and fast.rank.tolist() == slow.rank.tolist()
        assert sorted(found[0]) == sorted(found[1]) and len(slices) <= 60


def test_messages_are_made_a_piece_at_a_time():
    """A chunk's messages never lie in memory as a whole, and rows of sources give the sums that rows of messages give."""
    import tracemalloc

    rng = np.random.default_rng(2)
    values, at = rng.integers(0, 9, (16, 64)), np.repeat(np.arange(16), 10_000)
    dst = np.concatenate([np.sort(rng.permutation(200_000)[:10_000]) for _ in range(16)])
    local, n = np.ones(len(dst), np.int64), 0
    tracemalloc.start()
    for v, _, x in tiers.PartialSums(50, "fewest", 64).add(dst, values, local, at):
        n += len(v)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert n <= len(np.unique(dst)) and peak < len(dst) * 64 * 8 / 2
    few = slice(0, 160_000, 400)
    both = [tiers.PartialSums(7, "lru", 64) for _ in range(2)]
    for one, two in zip(both[0].add(dst[few], values, local[few], at[few]), both[1].add(dst[few], values[at[few]], local[few])):
        assert all(np.array_equal(x, y) for x, y in zip(one, two))


def test_engine_by_blocks_of_destinations(spark, sf_dir, monkeypatch):
    """Blocks, and sums too many to be held in a task, change neither rows nor the partial sums counted in a task's store."""
    from layerflow.plans import engine

    g, m = GRAPHS["copurchase"](spark, sf_dir), layerwise.model("sage", 8, hidden=128)
    runs = {}
    for held, blocks in ((1 << 30, 1), (1 << 14, 64), (1, 3)):
        monkeypatch.setattr(engine, "HELD", held)
        monkeypatch.setattr(engine, "BLOCKS", blocks)
        assert (engine.blocks_for(g.vertices.count(), 128) > 1) == (blocks > 1)
        out, report = engine.run_engine(g, m, "random", slots=5, chunk_rows=16, spill_rows=7, buffer_rows=64)
        runs[blocks] = sorted(map(tuple, out.collect())), report.messages
    assert runs[1][0] == runs[64][0] == runs[3][0] and len(runs[1][0]) == g.vertices.count()
    assert min(runs[64][1] + runs[3][1]) > 0


def test_topology_of_positions(spark, tmp_path):
    """Lists under new ids, cut in blocks, with counts by range; ends that aren't vertices drop their edges."""
    from layerflow import store
    from layerflow.plans import engine

    rng = np.random.default_rng(4)
    pairs = sorted({(int(a), int(b)) for a, b in rng.integers(0, 40, (300, 2))})
    place = dict(zip(range(0, 36), rng.permutation(36).tolist()))
    pos = spark.createDataFrame([*place.items()], "vid long, pos long")
    g = Graph("given", pos.select("vid"), spark.createDataFrame(pairs, "src long, dst long"), None)
    want = sorted((place[a], place[b]) for a, b in pairs if a in place and b in place)
    for blocks in (1, 3):
        path = store.new_path(spark, "topology")
        engine.write_topology(g, path, 36, 4, pos, None, blocks)
        rows = spark.read.parquet(path).collect()
        assert sorted((r.vid, d) for r in rows for d in r.dst) == want
        assert all(r.range_id == r.vid // 9 and r.dst == sorted(r.dst) and {d % blocks for d in r.dst} == {r.block} for r in rows)
        assert all(n == sum(b == d and a // 9 == r.range_id for a, b in want) for r in rows for d, n in zip(r.dst, r.local))


def test_sage_slots_replays_packed_chunks(spark, sf_dir, monkeypatch):
    """The report equals that of a trace of rows, without making one."""
    from layerflow.plans import workloads

    g = GRAPHS["trade"](spark, sf_dir)
    _, trace, peak = workloads._trace(g, "yield")
    want = [(k, w, s, *workloads._counts(trace, s)) for k, w, s in (("graphconv", 8, peak), ("sage", 16, peak // 2))]
    monkeypatch.setattr(workloads, "_trace", None)
    assert [tuple(r) for r in workloads.sage_slots(spark, sf_dir).collect()] == want


def test_peak_of_a_trace(spark, sf_dir):
    g = GRAPHS["copurchase"](spark, sf_dir)
    for order in (orders.order_original(g.vertices), orders.order_yield(g.edges, g.vertices)):
        pos = order.select("vid", "pos").cache()
        assert progress.trace_peak(progress.message_trace(g.edges, pos, 7)) == progress.active_peak(g.edges, pos, 7).first()["peak"]
    assert progress.trace_peak(progress.message_trace(g.edges.limit(0), pos, 7)) == 0


def test_blocks_of_chunks(spark, sf_dir):
    """One row a block, not a chunk, holds all chunks; shares are cut by shard and block however many there are."""
    g = GRAPHS["trade"](spark, sf_dir)
    pos = orders.order_original(g.vertices)
    chunks = progress.message_trace(g.edges, pos, 16).select("chunk").distinct().count()
    packed = tiers.packed_runs(g.edges, pos, 16)
    assert packed.count() < chunks and sum(len(r.chunk) // 8 for r in packed.collect()) == chunks
    for shards in (1, 70_000):
        n = 1000
        rng = np.random.default_rng(0)
        shard, chunk, k = rng.integers(0, shards, n).astype(np.int32), rng.integers(0, 9, n), np.arange(n)
        out = tiers._share(2, shard, chunk, k, k + 5, np.full(n, 7, np.int32), k % 2 == 0).to_pylist()
        assert len({(r["shard"], r["block"]) for r in out}) == len(out)
        got = sorted((r["shard"], r["block"] * 2 + (a >> 31), a & tiers._FAR) for r in out for a in np.frombuffer(r["at"], np.int64).tolist())
        assert got == sorted(zip(shard.tolist(), chunk.tolist(), k.tolist()))
        assert all(np.array_equal(np.frombuffer(r["dst"], np.int64), np.array([v + 5 for v in (np.frombuffer(r["at"], np.int64) & tiers._FAR).tolist() if v % 2], np.int64)) for r in out)


def test_lists_of_edges_both_ways(spark, sf_dir):
    """Ends dealt once give the distinct edges, scores and chunks of edges made as rows; repeats, loops, nulls, wide ids."""
    wide = 1 << 40
    given = [(1, 2), (2, 1), (1, 2), (3, 3), (3, None), (None, 4), (-5, 2), (wide, 2), (2, wide), (None, None)]
    for ends in (spark.createDataFrame(given, "src long, dst long"), spark.createDataFrame([], "src long, dst long")):
        lists = arrays.both_lists(ends)
        found = {}
        for r in lists.rows.collect():
            k, x = (np.frombuffer(r.k, np.int64), np.frombuffer(r.x, np.int64)) if r.x is not None else arrays.parted(np.frombuffer(r.k, np.int64))
            found |= dict(zip(zip(k.tolist(), x.tolist()), np.frombuffer(r.degree, np.int32).tolist()))
        edges = {tuple(e) for e in both_ways(ends).collect()}
        assert set(found) == edges and lists.pairs == len(edges)
        assert all(n == sum(u == v for u, _ in edges) for (v, _), n in found.items())
    g = GRAPHS["trade"](spark, sf_dir)
    lists, plain = arrays.both_lists(g.ends), orders.order_yield(g.edges, g.vertices).cache()
    assert sorted(orders.order_yield(None, g.vertices, lists=lists).collect()) == sorted(plain.collect())
    of_lists, of_edges = tiers.packed_runs(None, plain, 64, lists=lists), tiers.packed_runs(g.edges, plain, 64)
    assert sorted(map(tuple, of_lists.collect())) == sorted(map(tuple, of_edges.collect()))
    assert g.with_edges(g.edges.limit(1)).ends is None
    trace = progress.message_trace(g.edges, plain, 64)
    wanted = tiers.replay_tiers(trace, progress.trace_peak(trace) // 2, "lru").summary().first()
    assert QUERIES["replay_lru"](spark, sf_dir).first() == wanted


def test_replay_in_shards(spark, sf_dir):
    g = GRAPHS["trade"](spark, sf_dir)
    trace = progress.message_trace(g.edges, orders.order_yield(g.edges, g.vertices).select("vid", "pos"), 64).cache()
    n = trace.select("dst").distinct().count()
    for shards in (1, 5):
        r = tiers.replay_tiers(trace, 300, "fewest", shards=shards)
        s = r.summary().first()
        assert s.finished == n and s.reloads == s.evictions == r.reloads.agg(F.sum("reloads")).first()[0]
    cache = tiers.cache_replay(tiers.page_trace(g.edges, 64, 16), 40, "lru", sets=4)
    assert cache.agg(F.sum(F.col("hits") + F.col("misses"))).first()[0] == tiers.page_trace(g.edges, 64, 16).count()


def test_finisher_keeps_rows_over_buffers():
    import pyarrow as pa

    from layerflow.plans.engine import Finisher

    layer = layers.SageConv([np.eye(2, dtype=np.int64), 2 * np.eye(2, dtype=np.int64)], act="identity")
    rows = [(v, n, [n * v, n], [1, v]) for v, n in ((0, 0), (1, 2), (2, 3), (3, 1), (4, 5))]
    batch = pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())))], names=["vid", "n", "x", "own"])
    want = [(v, 1 + 2 * (v if n else 0), v + 2 * (1 if n else 0)) for v, n, *_ in rows]
    for size in (1, 2, 100):
        out = [x for b in Finisher(layer, True, size)([batch.slice(0, 3), batch.slice(3)]) for x in zip(*(b.column(c).to_pylist() for c in ("vid", "c0", "c1")))]
        assert out == want
    with pytest.raises(ValueError):
        Finisher(layer, True, 0)


def test_engine_runs_report_what_they_took(spark, sf_dir):
    from layerflow.plans import engine

    g = GRAPHS["copurchase"](spark, sf_dir)
    m = layerwise.model("graphconv", g.d, hidden=128)
    out, report = engine.run_engine(g, m, "original", slots=20, chunk_rows=32, buffer_rows=50)
    again, _ = engine.run_engine(g, m, "random", slots=1000)
    assert errors.differing_rows(out, again) == 0  # whatever the order and the budget
    assert report.status == "done" and len(report.seconds) == 2 and min(report.seconds) > 0 and {x["layer"] for x in report.stages} == {0, 1, 2}
    _, pulled = engine.pull_baseline(g, m, "original")
    assert pulled.messages[0] > 2 * report.messages[0]
    with pytest.raises(ValueError):
        engine.run_engine(g, m, slots=0)
    _, planned = layerwise.infer_layerwise(g, m)
    assert planned.status == "planned" and planned.seconds == []


def test_bad_arguments(spark):
    g = small(spark, 6, SIX)
    with pytest.raises(ValueError):
        aggregate.push_aggregate(g.edges, g.features, g.vertices, "median")
    with pytest.raises(ValueError):
        tiers.TierStore(0, "lru")
    with pytest.raises(ValueError):
        tiers.TierStore(1, "none")
    with pytest.raises(ValueError):
        progress.assign_chunks(orders.order_original(g.vertices), 0)


@pytest.mark.parametrize("kind", ["graphconv", "sage", "gin", "sgc"])
def test_engines_equal_reference(spark, sf_dir, kind):
    g = GRAPHS["embgraph"](spark, sf_dir)
    m = layerwise.model(kind, g.d)
    want = layerwise.reference_numpy(g, m)
    for engine in ("push", "pull"):
        out, _ = layerwise.infer_layerwise(g, m, engine)
        cols = value_columns(out)
        got = {r.vid: np.array([r[c] for c in cols]) for r in out.collect()}
        assert got.keys() == want.keys() and all((got[v] == want[v]).all() for v in want)


def test_float_accuracy_and_attention(spark, sf_dir):
    g = GRAPHS["embgraph"](spark, sf_dir)
    cols = value_columns(g.features)
    g = Graph(g.name, g.vertices, g.edges, g.features.select("vid", "tile", *[(F.col(c) / 65536.0).cast("float").alias(c) for c in cols]), g.d)
    for kind in ("graphconv", "sage", "gat"):
        m = layerwise.model(kind, g.d, weights="glorot", shift=None)
        want = layerwise.reference_numpy(g, m, exact=False)
        out, _ = layerwise.infer_layerwise(g, m, exact=False)
        names = value_columns(out)
        ref = spark.createDataFrame([(int(v), *map(float, x)) for v, x in want.items()], "vid long, " + ", ".join(f"{c} double" for c in names))
        assert errors.mean_max_abs_error(out, ref).first().error < 8e-5
        assert errors.mean_avg_rel_error(out, ref, 1e-3).first().error < 2.8e-6 * 10


def test_vertexwise_and_relabel_agree(spark, sf_dir):
    g = GRAPHS["geo"](spark, sf_dir)
    m = layerwise.model("graphconv", g.d)
    full, _ = layerwise.infer_layerwise(g, m)
    n = g.vertices.count()
    assert errors.differing_rows(full, vertexwise.infer_vertexwise(g, m, n, n // 2 + 1)) == 0
    out, reports = vertexwise.superbatch_baseline(g, m, n, n // 4 + 1, 2, 20, 50)
    assert errors.differing_rows(full, out) == 0 and sum(r.misses for r in reports) > 0
    pos = orders.order_random(g.vertices, 3)
    moved = Graph("moved", orders.relabel_rows(g.vertices, pos), orders.relabel_edges(g.edges, pos), orders.relabel_rows(g.features, pos), g.d)
    back, _ = layerwise.infer_layerwise(moved, m)
    assert errors.differing_rows(orders.relabel_rows(full, pos), back) == 0


def test_masked_equals_removed(spark, sf_dir):
    g = GRAPHS["copurchase"](spark, sf_dir)
    flag = F.col("src") % 3 != 0
    a = aggregate.push_aggregate(sampling.masked(sampling.mask_edges(g.edges, flag)), g.features, g.vertices)
    assert errors.differing_rows(a, aggregate.push_aggregate(g.edges.where(flag), g.features, g.vertices)) == 0


def test_bounded_combiner(spark, sf_dir):
    g = GRAPHS["copurchase"](spark, sf_dir)
    want = aggregate.push_aggregate(g.edges, g.features, g.vertices, "sum")
    for slots, policy in ((1, "lru"), (50, "fewest"), (10_000, "random")):
        assert errors.differing_rows(want, tiers.push_combine_bounded(g.edges, g.features, g.vertices, slots, policy)) == 0


def test_nulls_and_duplicates(spark):
    e = clean_edges(spark.createDataFrame([(1, 2), (1, 2), (None, 2), (3, None)], "src long, dst long"))
    assert [(r.src, r.dst) for r in e.collect()] == [(1, 2)]
    assert clean_edges(spark.createDataFrame([(1, 2), (1, 2)], "src long, dst long"), dedup=False).count() == 2


def test_rcm_and_yield_are_bijections(spark, sf_dir):
    g = GRAPHS["geo"](spark, sf_dir)
    n = g.vertices.count()
    for o in (orders.order_rcm(g.edges, g.vertices), orders.order_yield(g.edges, g.vertices), orders.order_random(g.vertices)):
        assert sorted(r.pos for r in o.select("pos").collect()) == list(range(n))
    greedy = orders.order_greedy_small(EIGHT, 8)
    assert sorted(greedy) == list(range(8))


def plain_rcm(pairs, n):
    """Reversed breadth-first order of each component from its vertex of lowest degree, one vertex at a time."""
    near = {v: set() for v in range(n)}
    for a, b in pairs:
        if a != b:
            near[a].add(b)
            near[b].add(a)
    key, found, seen = (lambda v: (len(near[v]), v)), [], set()
    for v in range(n):
        if v in seen:
            continue
        part, todo = {v}, [v]
        while todo:
            todo += (new := near[todo.pop()] - part)
            part |= new
        order = [min(part, key=key)]
        for u in order:
            order += sorted(near[u] - set(order), key=key)
        seen |= part
        found.append(order[::-1])
    return [v for order in reversed(found) for v in order]


@pytest.mark.parametrize("shape", ["geo", "path", "cycles", "none"])
def test_rcm_against_plain(spark, sf_dir, shape):
    n = 60
    pairs = {"path": [((i * 7) % n, ((i + 1) * 7) % n) for i in range(40)], "cycles": [(i, i // 5 * 5 + (i + 1) % 5) for i in range(n)], "none": []}
    if shape == "geo":
        g = GRAPHS["geo"](spark, sf_dir)
        edges, vertices, n = g.edges, g.vertices, g.vertices.count()
        pairs[shape] = [(r.src, r.dst) for r in edges.collect()]
    else:
        edges, vertices = spark.createDataFrame(pairs[shape], "src long, dst long"), spark.range(n).withColumnRenamed("id", "vid")
    got = [r.vid for r in orders.order_rcm(edges, vertices).orderBy("pos").collect()]
    assert got == plain_rcm(pairs[shape], n)


def test_running_sum_levels(spark):
    rows = spark.range(1000).selectExpr("id AS pos", "(id * 31) % 17 - 5 AS x")
    total, want = 0, []
    for i in range(1000):
        total += (i * 31) % 17 - 5
        want.append(total)
    for levels in (2, 3, 5):
        assert [r.s for r in running_sum(rows, "pos", "x", "s", 4, levels).orderBy("pos").collect()] == want


def test_completion_beyond_a_long(spark, monkeypatch):
    """Destinations that together count more than 2**63, without making that many."""
    from decimal import Decimal

    g = small(spark, 8, EIGHT)
    pos = orders.order_original(g.vertices)
    curve = lambda: [r.done for r in progress.completion_curve(g.edges, pos).orderBy("pos").collect()]
    plain = curve()
    assert dict(progress.completion_curve(g.edges, pos).dtypes)["done"] == "bigint"
    monkeypatch.setattr(progress, "UNIT", orders.UNIT << 22)
    wide, d_in = curve(), {v: sum(b == v for _, b in EIGHT) for _, v in EIGHT}
    want = [sum((orders.UNIT << 22) // d_in[b] for a, b in EIGHT if a <= p) for p in range(8)]
    assert wide == [Decimal(x) for x in want] and want[-1] > 2**63 and plain[-1] < 2**43
    # seven destinations of 2**60 still fit, though eight vertices wouldn't
    monkeypatch.setattr(progress, "UNIT", 1 << 60)
    assert dict(progress.completion_curve(g.edges, pos).dtypes)["done"] == "bigint"


def test_yield_shortens_spans(spark):
    g = GRAPHS["trade"](spark, "/root/testdata/sf0.01")
    mean = lambda o: (lambda r: r.total / r.n)(progress.span_summary(g.edges, o).first())
    assert mean(orders.order_random(g.vertices)) > 2.5 * mean(orders.order_yield(g.edges, g.vertices))


def test_states(spark):
    log = spark.createDataFrame([(1, 1, "resident"), (1, 2, "parked"), (1, 3, "resident"), (1, 4, "completed"), (2, 1, "parked")], "vid long, step int, state string")
    assert [r.move for r in progress.illegal_transitions(log).collect()] == ["not started>parked"]


def test_bucket_queue():
    q = BucketQueue(5)
    for v, p in ((3, 2), (1, 2), (7, 5), (4, 1)):
        q.insert(v, p)
    q.decrease(7, 5)
    assert list(q.lowest()) == [7, 4, 1, 3]
    assert q.remove(1) == 2 and 1 not in q and len(q) == 3


def test_cache_replay(spark):
    a = spark.createDataFrame([(b, i) for b, items in enumerate([[1, 2], [3], [1, 2]]) for i in items], "batch long, item long")
    total = lambda p: tiers.cache_replay(a, 2, p).agg(F.sum("misses")).first()[0]
    assert total("farthest") <= total("lru")
    assert tiers.cache_replay(a, 10, "lru").agg(F.sum("misses")).first()[0] == 3


def test_spills(spark, sf_dir):
    g = GRAPHS["copurchase"](spark, sf_dir)
    n = g.vertices.count()
    path = storage.write_layer(spark, g.features, 1, n, 4, 20)
    m = storage.spill_manifest(spark, path).collect()
    assert sum(r.n_rows for r in m) == n and all(r.min_vid // -(-n // 4) == r.max_vid // -(-n // 4) == r.range_id for r in m)
    got = storage.read_chunk(spark, path, 30, 90, n, 4)
    assert sorted(r.vid for r in got.collect()) == list(range(30, 90))
    storage.scan_only(spark, path)


def test_argmax_and_softmax(spark):
    y = spark.createDataFrame([(1, 0, 1.0, 3.0), (2, 0, 2.0, 2.0)], "vid long, tile int, c0 double, c1 double")
    assert {r.vid: r.label for r in layers.argmax(y).collect()} == {1: 1, 2: 0}
    s = layers.relu_log_softmax(y).where("vid = 2").first()
    assert abs(s.c0 - np.log(0.5)) < 1e-12


def test_vector_functions(spark):
    from layerflow.functions.vectors import pack_half, register, unpack_half, vec_add, vec_matmul, vec_normalise, vec_scale, vec_sum

    df = spark.createDataFrame([(1, [3.0, 4.0]), (1, [1.0, 0.5]), (2, [0.0, 0.0])], "k int, v array<float>")
    r = df.select(vec_add("v", "v").alias("a"), vec_scale("v", F.lit(2.0)).alias("s"), vec_normalise("v").alias("n"), vec_matmul(np.eye(2)[::-1])("v").alias("m"), unpack_half(pack_half("v")).alias("h"), "v").collect()
    assert r[0].a == r[0].s == [6.0, 8.0] and np.allclose(r[0].n, [0.6, 0.8]) and r[0].m == [4.0, 3.0] and r[1].h == r[1].v
    assert {x.k: x.v for x in vec_sum(df, "k", "v", 2).collect()} == {1: [4.0, 4.5], 2: [0.0, 0.0]}
    register(spark)
    assert spark.sql("SELECT vec_dot(array(1.0D, 2.0D), array(3.0D, 4.0D)) AS d").first().d == 11.0


def test_costs_are_measured(spark, sf_dir):
    import os

    from layerflow.plans.measure import ProcessTrace, measured

    g = GRAPHS["copurchase"](spark, sf_dir)
    with ProcessTrace(os.getpid(), 0.05) as trace:
        push, pull = (measured(spark, lambda e=e: layerwise.infer_layerwise(g, layerwise.model("graphconv", g.d, layers=1), e)[0]) for e in ("push", "pull"))
    assert push.shuffle_bytes < pull.shuffle_bytes and push.read_bytes > 0 and push.seconds > 0
    assert trace.peak_bytes() > 0 and trace.cpu_percent() >= 0
    assert errors.extrapolate(21600, 0.25, 1) == 86400 and errors.extrapolate(10, 0.5, 1) == 10
    plan = errors.memory_plan(10, 4, 2, 100, 3, 7, 5)
    assert plan["total"] == 80 + 300 + 7 + 65
