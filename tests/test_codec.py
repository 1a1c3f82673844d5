"""Worked examples and invariants of the codec."""

import random
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from roadtraj.operators import grams, huffman, packed, shortest, spatial, temporal, twostage
from roadtraj.sources import network, trips

SF = "/root/testdata/sf0.001"


def pair_table(edges):
    """Recorded paths of a small network (e, tail, head, w), by relaxing until nothing changes."""
    vertices = sorted({v for _, t, h, _ in edges for v in (t, h)})
    dist = {(u, u): 0 for u in vertices}
    for _ in vertices:
        for u in vertices:
            for _, t, h, w in edges:
                if (u, t) in dist:
                    dist[u, h] = min(dist.get((u, h), dist[u, t] + w), dist[u, t] + w)
    last = {(u, v): min((e for e, t, h, w in edges if h == v and dist.get((u, t), 10**9) + w == d), default=-1) if u != v else -1 for (u, v), d in dist.items()}
    columns = lambda rows, names: {n: np.array(c, np.int64) for n, c in zip(names, zip(*rows, strict=True), strict=True)}
    return spatial.PairTable(columns([(u, v, d, last[u, v]) for (u, v), d in dist.items()], ("u", "v", "dist", "last_edge")), columns(edges, ("e", "tail", "head", "w")))


def _lists(*paths):
    return pa.array(paths, pa.list_(pa.int32()))


def test_skip_example():
    # The path 15, 12, 9, 6, 3 is the recorded path from 15 to 3.
    pairs = pair_table([(15, 0, 1, 1), (12, 1, 2, 1), (9, 2, 3, 1), (6, 3, 4, 1), (3, 4, 5, 1)])
    assert spatial.skip(_lists([15, 12, 9, 6, 3], None, [12], [], [9, 6]), pairs).to_pylist() == [[15, 3], None, [12], [], [9, 6]]
    assert pairs.sp_end(np.array([15, 15, 15]), np.array([9, 6, 15])).tolist() == [12, 9, -1]


def test_skip_keeps_returns():
    """A trip that comes back to an edge is not skipped into it, with a dense and with a sorted pair table."""
    pairs = pair_table([(0, 0, 1, 1), (1, 1, 2, 1), (2, 2, 0, 1), (3, 1, 3, 1)])
    trips_ = _lists([0, 1, 2, 0, 3], [0, 1, 2, 0, 1, 2, 0], [1, 2, 0, 3])
    for _ in range(2):
        short = spatial.skip(trips_, pairs)
        assert len(short[0]) > 2 and spatial.restore(short, pairs).to_pylist() == trips_.to_pylist()
        pairs.index = None


def test_walks_between_vertices():
    pairs = pair_table([(0, 0, 1, 1), (1, 1, 2, 1), (2, 2, 0, 1), (3, 1, 3, 1)])
    path, offsets = pairs.walk(np.array([0, 2, 1]), np.array([3, 2, 0]))
    assert path.tolist() == [0, 3, 1, 2] and offsets.tolist() == [0, 2, 2, 4]
    with pytest.raises(ValueError):
        pairs.walk(np.array([3]), np.array([0]))


# Three training paths over edges 1 to 10.
TRAINING = [[1, 5, 8, 6, 3], [1, 5, 2, 1, 4, 8], [2, 1, 4, 6]]


@pytest.fixture(scope="module")
def example(spark):
    paths = spark.createDataFrame([(i, p) for i, p in enumerate(TRAINING)], "trip_id long, path array<int>")
    edges = spark.createDataFrame([(e,) for e in range(1, 11)], "e int")
    return grams.mine_grams(paths, 3, edges)


def test_mining_example(example):
    found = {r["gram"]: r["freq"] for r in example.collect()}
    assert len(found) == 27
    assert found["1"] == 4 and found["2-1-4"] == 2 and found["7"] == found["9"] == found["10"] == 0


def test_suffix_links(example):
    links = {r["gram"]: r["suffix"] for r in grams.link_grams(example).collect()}
    assert links["2-1-4"] == "1-4" and links["1-4"] == "4" and links["1"] is None


def test_huffman_example(example):
    book = huffman.codebook(example, 3)
    assert book.total_bits() == 163
    assert sum(2.0**-n for n in book.lengths.values()) == 1
    codes = sorted(format(book.codes[g], f"0{n}b") for g, n in book.lengths.items())
    assert not any(b.startswith(a) for a, b in zip(codes, codes[1:], strict=False))
    low, mean = huffman.entropy_bounds(book)
    assert low <= mean < low + 1
    ordered = sorted(book.freq, key=book.freq.get)
    assert all(book.lengths[a] >= book.lengths[b] for a, b in zip(ordered, ordered[1:], strict=False) if book.freq[a] < book.freq[b])


def test_decomposition_example(example):
    book = huffman.codebook(example, 3)
    path = [1, 4, 7, 5, 8, 6, 3, 1, 5, 2, 10]
    pieces, offsets = grams.pieces_backward(np.array(path, np.int32), np.array([0, len(path)]), book)
    assert book.names.take(pa.array(pieces)).to_pylist() == ["1-4", "7", "5", "8-6-3", "1-5-2", "10"]
    data, bounds, n_bits = book.pack(pieces, offsets)
    assert n_bits[0] == sum(book.lengths[g] for g in ("1-4", "7", "5", "8-6-3", "1-5-2", "10"))
    assert "".join(f"{x:08b}" for x in data)[: n_bits[0]] == "".join(format(book.codes[g], f"0{book.lengths[g]}b") for g in ("1-4", "7", "5", "8-6-3", "1-5-2", "10"))
    assert book.expand(*book.unpack(data, bounds, n_bits))[0].tolist() == path


def _slow_pieces(path, book, how):
    text, out = [str(e) for e in path], []
    if how == "forward":
        while text:
            n = next(n for n in range(min(book.theta, len(text)), 0, -1) if "-".join(text[:n]) in book.lengths)
            out.append("-".join(text[:n]))
            text = text[n:]
    elif how == "backward":
        while text:
            n = next(n for n in range(min(book.theta, len(text)), 0, -1) if "-".join(text[-n:]) in book.lengths)
            out.insert(0, "-".join(text[-n:]))
            text = text[:-n]
    else:
        best = [(0, [])]
        for k in range(1, len(text) + 1):
            best.append(min(((best[k - n][0] + book.lengths[g], best[k - n][1] + [g]) for n in range(1, min(book.theta, k) + 1) if (g := "-".join(text[k - n : k])) in book.lengths), key=lambda x: x[0]))
        out = best[-1][1]
    return out


@pytest.mark.parametrize("theta", [1, 2, 3, 6])
def test_tilings_and_codes_of_many_paths(theta):
    """Every tiling against a loop over one path, and codes there and back, empty paths included."""
    rng = random.Random(theta)
    paths = [[rng.randrange(6) if rng.random() < 0.7 else rng.randrange(12) for _ in range(rng.randrange(0, 30))] for _ in range(80)]
    counts = Counter("-".join(map(str, p[i : i + n])) for p in paths[:40] for n in range(1, theta + 1) for i in range(len(p) - n + 1))
    book = huffman.Codebook([*counts.items(), *((str(e), 0) for e in range(12) if str(e) not in counts)], theta)
    flat, offsets = np.array([e for p in paths for e in p], np.int32), np.concatenate([[0], np.cumsum([len(p) for p in paths])])
    for how, tiling in grams.TILINGS.items():
        pieces, bounds = tiling(flat, offsets, book)
        names = book.names.take(pa.array(pieces)).to_pylist()
        got = [names[a:b] for a, b in zip(bounds, bounds[1:], strict=False)]
        want = [_slow_pieces(p, book, how) for p in paths]
        if how == "cheapest":
            assert [sum(book.lengths[g] for g in x) for x in got] == [sum(book.lengths[g] for g in x) for x in want]
            assert ["-".join(x) for x in got] == ["-".join(map(str, p)) for p in paths]
        else:
            assert got == want
        back, ends = book.expand(*book.unpack(*book.pack(pieces, bounds)))
        assert back.tolist() == flat.tolist() and ends.tolist() == offsets.tolist()


def test_code_words_have_bounded_width():
    weights = [1, 1]
    while len(weights) < 70:
        weights.append(weights[-1] + weights[-2])
    with pytest.raises(ValueError, match="57 bits"):
        huffman.Codebook([(str(i), w) for i, w in enumerate(weights)], 1)


def test_counter_example_keeps_all():
    points = [{"d": d, "t": t} for d, t in ((0, 0), (1, 6), (10, 12), (12, 15))]
    assert temporal.compress_points(points, 1, 1) == points


def _random_points(rng):
    d = t = 0
    out = [{"d": 0, "t": 0}]
    for _ in range(rng.randrange(1, 25)):
        d, t = d + rng.choice((0, 0, 1, 5, 20)), t + rng.randrange(1, 12)
        out.append({"d": d, "t": t})
    return out


@pytest.mark.parametrize("tau,eta", [(0, 0), (3, 0), (0, 4), (5, 5), (10**6, 10**6)])
def test_temporal_bounds_and_twins(spark, tau, eta):
    rng = random.Random(tau * 31 + eta)
    rows = [(i, _random_points(rng)) for i in range(60)]
    df = spark.createDataFrame(rows, f"trip_id long, temporal {temporal.POINTS}")
    thin = temporal.temporal_compress(df, tau, eta)
    assert thin.exceptAll(temporal.opening_window(df, tau, eta)).count() == 0
    assert thin.exceptAll(temporal.temporal_compress(df, tau, eta, strategy="arrow")).count() == 0
    both = temporal.nstd(temporal.tsnd(df.join(thin.withColumnRenamed("temporal", "packed"), "trip_id")))
    worst = both.agg(F.max("tsnd"), F.max("nstd")).first()
    assert worst[0] <= tau + 1 and worst[1] <= eta + 1  # answers are rounded down
    ends = both.where("packed[0] <> temporal[0] OR element_at(packed, -1) <> element_at(temporal, -1)")
    assert ends.count() == 0


@pytest.fixture(scope="module")
def town(spark):
    edges = network.build_network(spark, SF)
    return edges, shortest.build_pairs(edges, "dijkstra").cache(), trips.trip_paths(spark, SF).cache()


def test_pairs(spark, town):
    edges, sp, _ = town
    assert sp.exceptAll(shortest.build_pairs(edges, "minplus")).count() == 0
    assert shortest.check_containment(sp, edges).count() == 0
    assert network.check_network(edges).count() == 0


def test_lossless_and_best(spark, town):
    edges, sp, paths = town
    short = spatial.sp_compress(paths, sp, edges)
    assert spatial.sp_decompress(short, sp, edges).exceptAll(paths).count() == 0
    best = spatial.sp_best_length(paths, sp, edges).withColumnRenamed("path", "best")
    assert short.join(best, "trip_id").where("size(path) <> best").count() == 0
    ahead = spatial.sp_compress_lookahead(trips.trip_steps(spark, SF), sp, edges, reach=64).withColumn("train", F.lit(True))
    assert trips.as_paths(ahead).select("trip_id", "path").exceptAll(short.select("trip_id", "path")).count() == 0


def test_bounded_pairs_stay_lossless(spark, town):
    edges, _, paths = town
    near = shortest.build_pairs(edges, "dijkstra", radius=7000)
    short = spatial.sp_compress(paths, near, edges)
    assert spatial.sp_decompress(short, near, edges).exceptAll(paths).count() == 0


def test_both_stages_in_one_pass(spark, town):
    edges, sp, paths = town
    short = spatial.sp_compress(paths, sp, edges)
    book, pairs = huffman.codebook(grams.mine_grams(short.where("train"), 3, edges), 3), spatial.PairTable.collect(sp, edges)
    packed_ = twostage.compress_paths(paths, pairs, book)
    assert packed_.exceptAll(grams.encode(grams.decompose(short, book), book).drop("path")).count() == 0
    assert twostage.decompress_paths(packed_, pairs, book).exceptAll(paths).count() == 0
    plain = twostage.compress_paths(paths, None, book, "cheapest")
    assert twostage.decompress_paths(plain, None, book).exceptAll(paths).count() == 0


def test_weighted_counts(spark, town):
    edges, sp, paths = town
    short = spatial.sp_compress(paths, sp, edges)
    book = huffman.codebook(grams.mine_grams(short.where("train"), 3, edges), 3)
    spans = packed.trip_spans(grams.decompose(short, book))
    counts = packed.edge_counts(spans, packed.build_aux(spans, sp, edges))
    raw = paths.select(F.explode("path").alias("e")).groupBy("e").agg(F.count(F.lit(1)).alias("n"))
    assert counts.exceptAll(raw).count() == 0 and raw.exceptAll(counts).count() == 0


def test_native_plans_hold_no_python(spark):
    points = trips.trip_temporal(spark, SF)
    plan = temporal.temporal_compress(points, 100, 100)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_packed_container_prunes(spark, town, tmp_path):
    from roadtraj.plans.container import packed_table, read_packed, write_packed

    edges, sp, paths = town
    short = spatial.sp_compress(paths, sp, edges)
    book = huffman.codebook(grams.mine_grams(short, 3, edges), 3)
    nodes = grams.decompose(short, book)
    spans = packed.trip_spans(nodes)
    placed = packed.placed_spans(spans, packed.build_aux(spans, sp, edges))
    table = packed_table(grams.encode(nodes, book), trips.trip_temporal(spark, SF), placed)
    write_packed(table, str(tmp_path / "packed"), 2)
    middle = table.agg(F.expr("percentile_approx(t_first, 0.5)")).first()[0]
    some = read_packed(spark, str(tmp_path / "packed"), t2=middle)
    assert 0 < some.count() < table.count()
    assert "PushedFilters: [IsNotNull(t_first), LessThanOrEqual(t_first" in some._jdf.queryExecution().executedPlan().toString()


def test_every_edge_in_reach_is_a_candidate(spark):
    from roadtraj.operators import matching

    # Nine edges start at one vertex; the one driven is the last of them by distance and by id.
    net = spark.createDataFrame([(i, 0, i + 1, 1000, 0, 0, 1000, 40 * i) for i in range(9)], "e long, tail long, head long, w long, x0 long, y0 long, x1 long, y1 long")
    fixes = spark.createDataFrame([(1, 0, 300, -50, 0), (1, 1, 1000, 400, 60)], "trip_id long, seq int, x long, y long, t long")
    got = {(r.seq, r.e) for r in matching.candidates(fixes, net, 450).collect()}
    assert got == {(s, e) for s in (0, 1) for e in range(9)}
    sp = spark.createDataFrame([(0, 0, 0, None)], "u long, v long, dist long, last_edge int")
    assert [r.e for r in matching.match_trips(fixes, net, sp, mode="viterbi").orderBy("seq").collect()] == [8, 8]


def test_sequences_beyond_64_bits(spark):
    """Cross products that pass 64 bits: the plan's wide fold against a loop over whole numbers."""
    rng = random.Random(11)
    rows = []
    for i in range(30):
        d, t, out = 0, 10**15, []
        for _ in range(20):
            out.append({"d": d, "t": t})
            d, t = d + rng.randrange(0, 10**9), t + rng.randrange(1, 10**11)
        rows.append((i, out))
    df = spark.createDataFrame(rows, f"trip_id long, temporal {temporal.POINTS}")
    for tau, eta in ((0, 0), (10**8, 10**10), (None, 10**10), (10**8, None)):
        got = {r.trip_id: [p.asDict() for p in r.temporal] for r in temporal.temporal_compress(df, tau, eta).collect()}
        want = {i: temporal.compress_points(p, tau, eta) for i, p in rows}
        assert got == want
        counts = {r.trip_id: r.n for r in df.select("trip_id", F.expr(temporal.angular_count(tau, eta)).alias("n")).collect()}
        assert counts == {i: len(p) for i, p in want.items()}


def test_one_bound_alone(spark):
    """No bound is the same as one that is never reached."""
    rng = random.Random(12)
    df = spark.createDataFrame([(i, _random_points(rng)) for i in range(40)], f"trip_id long, temporal {temporal.POINTS}")
    for none, far in (((3, None), (3, 10**9)), ((None, 4), (10**9, 4))):
        assert temporal.temporal_compress(df, *none).exceptAll(temporal.temporal_compress(df, *far)).count() == 0


def _square(spark):
    """Four streets of a block, one way round, and back again."""
    corners = [(0, 0), (1000, 0), (1000, 1000), (0, 1000)]
    rows = [(k, k, (k + 1) % 4, 1000, *corners[k], *corners[(k + 1) % 4], k) for k in range(4)]
    return spark.createDataFrame(rows, "e int, tail int, head int, w long, x0 long, y0 long, x1 long, y1 long, street int")


def test_reformat_of_loops_and_dropped_fixes(spark):
    """Two rounds of a block, starting within an edge, with fixes missing: distances go on, and come back as positions."""
    from roadtraj.operators import matching

    edges = _square(spark)
    sp = shortest.build_pairs(edges, "dijkstra").cache()
    drive = [(0, 300), (0, 900), (1, 500), (3, 200), (0, 100), (0, 800), (2, 400)]  # edge and way along it; 2 and 1 are passed unseen
    spot = {0: lambda p: (p, 5), 1: lambda p: (995, p), 2: lambda p: (1000 - p, 1004), 3: lambda p: (-3, 1000 - p)}
    fixes = spark.createDataFrame([(7, k, *spot[e](p), 100 + 10 * k, e) for k, (e, p) in enumerate(drive)], "trip_id long, seq int, x long, y long, t long, e int")
    matched = fixes.select("trip_id", "seq", "e")
    points = matching.reformat(matched, fixes, sp, edges)
    assert [r.d for r in points.orderBy("seq").collect()] == [300, 900, 1500, 3200, 4100, 4800, 6400]
    paths = matching.fill_gaps(matched, sp, edges)
    assert paths.first().path == [0, 1, 2, 3, 0, 1, 2]
    header = matching.trip_header(points, paths)
    assert header.first().asDict() == {"trip_id": 7, "start_off": 300, "n_edges": 7, "n_samples": 7, "t_first": 100, "t_last": 160, "d_total": 6100}
    began = matching.from_start(points, header)
    assert began.agg(F.min("d")).first()[0] == 0
    back = matching.on_path(began, header)
    assert back.select("seq", "d").exceptAll(points.select("seq", "d")).count() == 0
    # From fixes to a packed trip and an answer: within the bound of where the fix was.
    thin = temporal.temporal_compress(trips.as_temporal(back), 50, 5)
    aux = packed.raw_aux(edges)
    at = packed.where_at(spark.createDataFrame([(k, 7, 100 + 10 * k) for k in range(7)], "qid long, trip_id long, t long"), thin, packed.placed_spans(packed.raw_spans(paths), aux), aux)
    for r in at.collect():
        e, p = drive[r.qid]
        x, y = {0: (p, 0), 1: (1000, p), 2: (1000 - p, 1000), 3: (0, 1000 - p)}[e]
        assert abs(r.x - x) + abs(r.y - y) <= 52


def test_lossy_record_keeps_the_plane_bound():
    """Every sample of random walks within the bound, fewer samples with a wider one, and no sample lost at the ends."""
    from roadtraj.operators import baselines

    side, edges = 5, []
    for v in range(side * side):
        x, y = v % side, v // side
        for dx, dy in ((1, 0), (0, 1), (-1, 0), (0, -1)):
            if 0 <= x + dx < side and 0 <= y + dy < side:
                edges.append((len(edges), v, (y + dy) * side + x + dx, 1000))
    table = pair_table(edges)
    ground = baselines.Ground.__new__(baselines.Ground)
    ground.__dict__.update(table.__dict__)
    ground.line = np.array([(t % side * 1000, t // side * 1000, h % side * 1000, h // side * 1000) for _, t, h, _ in edges])
    rng, sizes = np.random.default_rng(4), {0: 0, 400: 0, 4000: 0}
    for _ in range(25):
        at, path = int(rng.integers(side * side)), []
        for _ in range(12):
            e, _, at, _ = edges[rng.choice([e for e, t, _, _ in edges if t == at])]
            path.append(e)
        path = np.array(path, np.int32)
        d = np.sort(rng.integers(0, 12_000, 15))
        t = np.cumsum(rng.integers(1, 90, 15))
        for eps in sizes:
            kept, line, reach = baselines._lossy(path, d, t, ground, eps)
            assert kept[0] == 0 and kept[-1] == 14 and (np.diff(reach) >= 0).all()
            moved = np.array([reach[k] if i == kept[k] else reach[k] + (reach[k + 1] - reach[k]) * (t[i] - t[kept[k]]) // (t[kept[k + 1]] - t[kept[k]]) for i in range(15) for k in [int(np.searchsorted(kept, i, side="right")) - 1]])
            gap = ground.places(line, moved) - ground.places(path, d)
            assert ((gap * gap).sum(1) <= (eps + 4) ** 2).all()
            sizes[eps] += len(kept)
    assert sizes[0] >= sizes[400] > sizes[4000]


def test_byte_codecs_come_back(spark):
    from roadtraj.operators import baselines

    rows = [(1, [(1.5, 2.0, 3.0), (4.0, 5.0, 6.25)]), (2, []), (3, None)]
    df = spark.createDataFrame(rows, "trip_id long, samples array<struct<x: double, y: double, t: double>>")
    for codec in baselines.CODECS:
        assert baselines.byte_decompress(baselines.byte_compress(df, codec), codec).where("trip_id < 3").exceptAll(df).count() == 0


def test_lossy_record_of_many_trips_at_once():
    """Trips that take their steps in common keep what each keeps alone; a trip of one sample and edges driven around count too."""
    from roadtraj.operators import baselines

    edges = [(v * 2 + k, v, (v + (1 if k == 0 else 5)) % 6, 1000 + 10 * v) for v in range(6) for k in range(2)]
    ground = baselines.Ground.__new__(baselines.Ground)
    ground.__dict__.update(pair_table(edges).__dict__)
    ground.line = np.array([(t * 1000, 0, h * 1000, 0) for _, t, h, _ in edges])
    rng, trips = np.random.default_rng(6), []
    for size in (1, 2, 3, 9, 25, 4):
        at, path = int(rng.integers(6)), []
        for _ in range(size):
            path.append(at * 2 + int(rng.integers(2)))
            at = edges[path[-1]][2]
        trips.append((np.array(path, np.int32), np.sort(rng.integers(0, 1000 * size + 1, 2 * size - 1)), np.cumsum(rng.integers(1, 90, 2 * size - 1))))
    bounds = lambda k: np.concatenate([[0], np.cumsum([len(trip[k]) for trip in trips])])
    flat = [np.concatenate([trip[k] for trip in trips]) for k in range(3)]
    for eps in (0, 500, 3000):
        line, line_at, kept, kept_at, reach = baselines._lossy_trips(flat[0], bounds(0), flat[1], flat[2], bounds(1), ground, eps)
        for i, trip in enumerate(trips):
            alone = baselines._lossy(*trip, ground, eps)
            own = slice(kept_at[i], kept_at[i + 1])
            assert (kept[own] - bounds(1)[i]).tolist() == alone[0] and line[line_at[i] : line_at[i + 1]].tolist() == alone[1].tolist() and reach[own].tolist() == alone[2].tolist()


def test_best_edges_of_many_trips_at_once():
    """Trips that take their fixes in common get what a loop with the exact square root gives each, ties to the candidate that stands first."""
    import math

    from roadtraj.operators import matching

    edges = [(v * 2 + k, v, (v + (1 if k == 0 else 5)) % 6, 1000) for v in range(6) for k in range(2)]
    pairs, rng = pair_table(edges), np.random.default_rng(8)
    sizes = [1, 4, 2, 7, 3]
    fix_at = np.concatenate([[0], np.cumsum(sizes)])
    count = rng.integers(1, 5, fix_at[-1])
    start = np.concatenate([[0], np.cumsum(count)])[:-1]
    e = np.concatenate([np.sort(rng.choice(12, c, replace=False)) for c in count]).astype(np.int32)
    gap = np.round(rng.integers(0, 3, len(e)) * 10_000.0)
    x, y = (rng.choice([3, 9, 119, 1757, 0], fix_at[-1]).astype(float) for _ in range(2))
    want = []
    for a, b in zip(fix_at, fix_at[1:], strict=False):
        ways = [(gap[k], [k]) for k in range(start[a], start[a] + count[a])]
        for i in range(a + 1, b):
            straight, onward = math.sqrt((x[i] - x[i - 1]) ** 2 + (y[i] - y[i - 1]) ** 2), []
            for k in range(start[i], start[i] + count[i]):
                costs = []
                for cost, way in ways:
                    f, g = edges[e[way[-1]]], edges[e[k]]
                    hop = 0 if f[2] == g[1] else pairs.dist[pairs.find(np.array([f[2]]), np.array([g[1]]))[0]]
                    costs.append(cost + (0.0 if f[0] == g[0] else abs(float(hop) + g[3] - straight) * 100.0))
                j = costs.index(min(costs))
                onward.append((costs[j] + gap[k], [*ways[j][1], k]))
            ways = onward
        want += [int(e[k]) for k in min(ways, key=lambda w: w[0])[1]]
    assert matching._best_edges(pairs, fix_at, start, count, e, gap, x, y).tolist() == want


def test_searches_give_the_recorded_pairs(spark):
    """Searches of many sources in common give the pairs of the joins: ties, edges side by side, dead ends, vertices out of reach; no pair is shuffled."""
    rng = random.Random(4)
    rows = [(e, rng.randrange(30), rng.randrange(30), rng.choice([1, 2, 3, 3, 50])) for e in rng.sample(range(500), 70)] + [(500, 30, 31, 7), (501, 30, 31, 7)]
    edges = spark.createDataFrame(rows, "e int, tail int, head int, w long").cache()
    for radius in (None, 5):
        found, want = shortest.build_pairs(edges, "dijkstra", radius), shortest.build_pairs(edges, "minplus", radius)
        assert sorted(map(tuple, found.collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr)
        assert "Join" not in found._jdf.queryExecution().executedPlan().toString()


def test_searches_of_a_large_network_are_spread(spark, tmp_path):
    spark.range(1500).select(F.col("id").alias("s_suppkey")).write.parquet(str(tmp_path / "supplier.parquet"))
    pairs = shortest.build_pairs(network.build_network(spark, str(tmp_path), "supplier"), "dijkstra")
    assert pairs.rdd.getNumPartitions() > 1


def test_trees_say_what_the_pair_table_says(spark):
    """A byte for each pair gives the same walks, skips and counts, dead ends and vertices out of reach included."""
    rng = random.Random(5)
    rows = [(e, rng.randrange(25), rng.randrange(25), rng.choice([1, 2, 3, 3, 9])) for e in rng.sample(range(300), 60)] + [(400, 25, 26, 7)]
    edges = spark.createDataFrame(rows, "e int, tail int, head int, w long").cache()
    sp = shortest.build_pairs(edges, "dijkstra").cache()
    trees, pairs = spatial.TreeTable.collect(edges), spatial.PairTable.collect(sp, edges)
    assert trees.pairs == sp.count() and trees.slots.itemsize == 1
    e = np.array([r[0] for r in rows])
    a, b = np.repeat(e, len(e)), np.tile(e, len(e))
    assert trees.sp_end(a, b).tolist() == pairs.sp_end(a, b).tolist()
    known = np.array([tuple(r) for r in sp.select("u", "v").collect()])
    for got, want in zip(trees.walk(known[:, 0], known[:, 1]), pairs.walk(known[:, 0], known[:, 1]), strict=True):
        assert got.tolist() == want.tolist()
    with pytest.raises(ValueError):
        trees.walk(np.array([26]), np.array([25]))


def test_tours_stop_at_every_line_item(spark, tmp_path):
    """Line items of one day are stops of their own, and a tour with one stop is a tour, with an empty path."""
    import datetime

    import duckdb

    from roadtraj import workloads

    day = datetime.datetime(1995, 3, 1)
    spark.range(10).select((F.col("id") + 1).alias("s_suppkey")).write.parquet(f"{tmp_path}/supplier.parquet")
    items = [(1, 1, 2, 1, 1.0, day), (1, 2, 7, 1, 1.0, day), (1, 3, 4, 1, 1.0, day + datetime.timedelta(days=1)), (2, 1, 3, 1, 1.0, day), (3, 2, 5, 1, 1.0, day), (3, 1, 8, 1, 1.0, day)]
    spark.createDataFrame(items, "l_orderkey long, l_linenumber int, l_suppkey long, l_partkey long, l_extendedprice double, l_shipdate timestamp_ntz").write.parquet(f"{tmp_path}/lineitem.parquet")
    _, paths = workloads.tour_paths(spark, str(tmp_path), each=True)
    got = {r.trip_id: r.path for r in paths.collect()}
    assert set(got) == {1, 2, 3} and got[2] == [] and got[1] and got[3]
    con = duckdb.connect()
    for t in ("supplier", "lineitem"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{tmp_path}/{t}.parquet/*.parquet')")
    want = dict(con.execute(workloads.ORACLE_SQL["codec_workload"]).fetchall())
    assert {r.what: r.n for r in workloads.QUERIES["codec_workload"](spark, str(tmp_path)).collect()} == want
    assert want["edges"] == sum(map(len, got.values()))


def test_tours_over_more_pairs_than_rows_fit(spark, tmp_path):
    """5,300 suppliers have 28 million pairs, more than a table of rows may hold; a tour drives the recorded path all the same."""
    import datetime

    from roadtraj import workloads

    n = 5300  # 53 wide
    spark.range(n).select(F.col("id").alias("s_suppkey")).write.parquet(str(tmp_path / "supplier.parquet"))
    day = lambda k: datetime.datetime(1995, 1, k)
    lines = [(1, 1, 0, 1, 1.0, day(1)), (1, 2, 2, 1, 1.0, day(2)), (1, 3, 2 + 53, 1, 1.0, day(3)), (2, 1, 7, 1, 1.0, day(1))]
    spark.createDataFrame(lines, "l_orderkey long, l_linenumber int, l_suppkey long, l_partkey long, l_extendedprice double, l_shipdate timestamp_ntz").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = workloads.QUERIES["tour_edges"](spark, str(tmp_path)).collect()
    # East from 0 and from 1, then north from 2: edges 0, 4 and 9.
    assert [tuple(r) for r in got] == [(1, 3, 0 * 1 + 4 * 2 + 9 * 3)]
    assert tuple(workloads.QUERIES["tour_sp_ratio"](spark, str(tmp_path)).first()) == (3, 2)


@pytest.mark.parametrize("chunk_bytes", [1 << 27, 600])
def test_overlaps_of_trips_against_all_pairs(spark, chunk_bytes):
    """Copies, nested sets, returns to an edge and trips alone, in one chunk and in many; only answers are shuffled."""
    from roadtraj.operators import overlaps

    rng = random.Random(7)
    trips_ = [(i, [rng.randrange(9) if i % 4 else rng.randrange(300) for _ in range(rng.randrange(9))]) for i in range(60)]
    trips_ += [(i + 100, trips_[i % 20][1][::-1] * 2) for i in range(50)] + [(900, [7000]), (901, None)]
    paths = spark.createDataFrame(trips_, "trip_id long, path array<int>").repartition(3)
    sets = {i: set(p) for i, p in trips_ if p}
    both = {(a, b): len(sets[a] & sets[b]) for a in sets for b in sets if a != b and sets[a] & sets[b]}
    found = overlaps.alike_trips(paths, 70, chunk_bytes)
    assert sorted(map(tuple, found.collect())) == sorted((a, b, n) for (a, b), n in both.items() if a < b and 100 * n >= 70 * (len(sets[a]) + len(sets[b]) - n))
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    want = [(a, r + 1, b, n) for a in sets for r, (n, b) in enumerate(sorted(((n, b) for (c, b), n in both.items() if c == a), key=lambda x: (-x[0], x[1]))[:3])]
    found = overlaps.similar_trips(paths, 3, chunk_bytes)
    assert sorted(map(tuple, found.collect())) == sorted(want)
    assert "Join" not in found._jdf.queryExecution().executedPlan().toString()


def test_long_street_runs_keep_a_small_plan(spark):
    """A run of 100 edges takes seven rounds; the plan must not hold each round's joins over again."""
    from roadtraj.operators import baselines

    edges = spark.createDataFrame([(i, i, i + 1, 5) for i in range(120)], "e int, tail int, head int, street int")
    steps = spark.createDataFrame([(1, i + 1, i) for i in range(100)] + [(2, i + 1, i + 50) for i in range(70)], "trip_id long, pos int, e int")
    back = baselines.street_expand(baselines.street_runs(steps, edges), edges)
    assert back._jdf.queryExecution().optimizedPlan().toString().count("Join") <= 4
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, steps.collect()))
