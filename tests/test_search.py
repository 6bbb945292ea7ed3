"""Parameters, hand cases, kernels and searches against plain loops, and what must not depend on how a query is run."""

import math
from dataclasses import replace

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from objann.functions.params import collision_prob, derive_params, gamma_min, point_error_rates, radius_ladder
from objann.operators import buffers, gamma, kernel, search
from objann.operators.hashing import inverted, make_projections, window_hits
from objann.operators.index import build_index, read_postings
from objann.operators.pointknn import ClosePairs, Nearest, Stops, hashed_knn, hashed_lists, linear_knn
from objann.operators.search import _Search, object_knn, object_knn_of
from objann.plans import catalogue, search_sql, workloads
from objann.plans.workloads import family_points, projections
from objann.sources.families import TWIN, Family, text_points, validate_points

SF = "/root/testdata/sf0.01"
POINTS = "object_id long, point_id long, vec array<long>"


@pytest.mark.parametrize("n, static, query", [(50, (62, 32), (35, 23)), (100, (75, 39), (43, 29)), (1000, (112, 61), (63, 44)), (28049, (158, 88), (89, 64))])
def test_parameters(n, static, query):
    for kind, expected in (("static", static), ("query", query)):
        p = derive_params(kind, beta=25 / n)
        assert (p.m, p.l) == expected
        near, far = point_error_rates(p)
        assert near >= 1 - p.delta - 0.02 and far >= 1 - p.beta / 2 - 0.02
    assert math.isclose(collision_prob("static", 1, 2.184), 0.6394, abs_tol=1e-4)
    with pytest.raises(ValueError):
        derive_params("static", c=1.5)


def test_parameters_follow_the_tables(spark):
    import duckdb

    own = workloads.parameter_table(spark, SF)
    db = duckdb.connect()
    for name in ("lineitem", "events"):
        db.sql(f"CREATE VIEW {name} AS SELECT * FROM '{SF}/{name}.parquet'")
    found = db.sql(search_sql.parameters())
    assert own.columns == found.columns and sorted(map(tuple, own.collect())) == sorted(found.fetchall())
    assert {r.family: r.n_objects for r in own.collect()}["supp"] == 100


def test_radii_go_on_until_the_widest_span():
    assert radius_ladder(2, 30) == [1, 2, 4, 8, 16, 32] and radius_ladder(1.5, 1) == [1]
    near, far = Family("near", 4, 1000, 2.0), Family("far", 4, 1000, 2000.0)
    p = derive_params("static")
    for family in (near, far):
        proj = make_projections(family, p)
        longest = np.sqrt((proj.a.astype(float) ** 2).sum(axis=1).max()) / 4096
        assert 2**proj.levels >= longest * family.diameter / p.w and (proj.levels == 0 or 2 ** (proj.levels - 1) < longest * family.diameter / p.w)


def test_the_guarantee_says_nothing_over_one():
    with pytest.warns(UserWarning):
        assert gamma_min(12, 12, 0.1, 0.2, 0.25) > 1
    assert gamma_min(600, 541, 0.1, 0.2, 0.25) < 0.05


def test_hand_case(spark):
    u = Family("hand", 2, 100)
    p = spark.createDataFrame([(1, 10, [0, 0]), (1, 11, [0, 300])], POINTS)
    q = spark.createDataFrame([(9, 1, [0, 0]), (9, 2, [200, 0])], POINTS)
    for share, square in (((1, 4), 0), ((1, 2), 4), ((3, 4), 9), ((1, 1), 13)):
        assert [r.sq_dist for r in gamma.gamma_distance(p, q, u, share).collect()] == [square * 10000]
        low, high = gamma.gamma_distance_sketch(p, q, u, share).first()[2:]
        assert low <= math.sqrt(square) < high
    assert gamma.object_similarity(p, q, u, 2).first()[2:] == (2, 4)
    assert gamma.object_similarity(p, q, u, 3).first()[2:] == (3, 4)
    assert gamma.gamma_distance(p, q.where("false"), u, (1, 2)).count() == 0 and gamma.gamma_distance(p.where("false"), q, u, (1, 2)).count() == 0


def scattered(spark, seed=3, objects=40, unit=500):
    rng = np.random.default_rng(seed)
    rows, n = [], 0
    for o in range(objects):
        centre = rng.integers(-6 * unit, 6 * unit, 6)
        for _ in range(int(rng.integers(1, 14))):
            rows.append((o, n, (centre + rng.integers(-unit, unit, 6)).tolist()))
            n += 1
    return spark.createDataFrame(rows, POINTS), {o: np.array([v for a, _, v in rows if a == o]) for o in range(objects)}


def test_share_distance_properties(spark, monkeypatch):
    family = Family("loose", 6, 500, 60.0)
    p, own = scattered(spark)
    q = p.where("object_id < 6")
    tables = {g: {(r.q_obj, r.object_id): r.sq_dist for r in gamma.gamma_distance(p, q, family, g).collect()} for g in ((1, 10), (1, 2), (1, 1))}
    for share, table in tables.items():
        for (a, b), found in table.items():
            pairs = np.sort(((own[a][:, None] - own[b][None, :]) ** 2).sum(axis=2).ravel())
            assert found == pairs[max(1, -(-share[0] * len(pairs) // share[1])) - 1]
    for pair, low in tables[1, 10].items():
        assert low <= tables[1, 2][pair] <= tables[1, 1][pair]
        assert pair[1] >= 6 or tables[1, 2][pair[::-1]] == tables[1, 2][pair]
    monkeypatch.setattr(kernel, "BLOCK", 40)  # many blocks, and query points in batches
    batches = list(kernel.query_batches(q, 5))
    assert len(batches) > 2 and sum(len(b.q_obj) for b in batches) == q.count()


def test_a_task_keeps_the_nearest_objects_only(spark, monkeypatch):
    p, _ = scattered(spark, objects=80)
    copies = p.where("object_id < 5").select((F.col("object_id") + 200).alias("object_id"), (F.col("point_id") + 5000).alias("point_id"), "vec")
    p, family = p.union(copies).repartition(3), Family("loose", 6, 500, 60.0)
    q = p.where("object_id < 6")
    every = sorted((r.q_obj, r.sq_dist, r.object_id) for r in gamma.gamma_distance(p, q, family, (1, 3)).collect())
    want = [row for o in range(6) for row in [r for r in every if r[0] == o][:4]]
    found = gamma.exact_object_knn(p, q, family, (1, 3), 4).collect()
    assert sorted((r.q_obj, r.sq_dist, r.object_id) for r in found) == want  # copies tie, the smaller id first
    batch = next(kernel.query_batches(q))
    near = gamma.object_distances(p, batch, (1, 3), 4)
    assert near.count() <= 6 * 4 * near.rdd.getNumPartitions() and gamma.object_distances(p, batch, (1, 3)).count() == len(every)  # a row a pair of objects
    monkeypatch.setattr(gamma, "LARGE", 9)  # objects of more points are spread
    assert sorted((r.q_obj, r.sq_dist, r.object_id) for r in gamma.gamma_distance(p, q, family, (1, 3)).collect()) == every


def test_ranks_in_blocks_and_slices(monkeypatch):
    rng = np.random.default_rng(5)
    sizes = np.array([1, 3, 3, 3, 7, 40])
    x, q = rng.integers(-50, 50, (sizes.sum(), 4)), rng.integers(-50, 50, (9, 4))
    d = ((x[:, None] - q[None]) ** 2).sum(axis=2)
    ranks, begins = np.maximum(1, sizes * 9 // 4), np.cumsum(sizes) - sizes
    want = [np.sort(d[b : b + n].ravel())[r - 1] for b, n, r in zip(begins, sizes, ranks)]
    for pairs, most in ((1 << 18, 1 << 24), (60, 1 << 24), (60, 30)):
        monkeypatch.setattr(gamma, "PAIRS", pairs)
        monkeypatch.setattr(gamma, "MOST_PAIRS", most)
        assert gamma.share_distances(gamma._sides(x, False), sizes, gamma._sides(q, True), ranks).tolist() == want


@pytest.mark.parametrize("kind, c", [("static", 2), ("static", 3), ("query", 2), ("query", 1.5)])
@pytest.mark.parametrize("mode", ["carry", "restart"])
def test_close_events_against_plain_counting(kind, c, mode):
    rng = np.random.default_rng(7)
    params = derive_params(kind, c=c, beta=0.3)
    proj = make_projections(Family("kernel", 5, 700, 40.0), params)
    q, x = rng.integers(-9000, 9000, (7, 5)), rng.integers(-9000, 9000, (130, 5))
    x[:7] = q + rng.integers(-300, 300, (7, 5))
    hq, hx = proj.hashes(q), proj.hashes(x)
    present = rng.random(hx.shape) < 0.97
    m, limits = params.m, proj.limits()
    want = set()
    for a in range(len(q)):
        for b in range(len(x)):
            hit = [[(hq[a, j] // r == hx[b, j] // r if kind == "static" else 2 * abs(hq[a, j] - hx[b, j]) <= r) and present[b, j] for j in range(m)] for r in limits]
            count, done = 0, False
            for t in range(len(limits)):
                if mode == "restart":
                    count, done = 0, False
                for j in range(m):
                    count += hit[t][j] and (mode == "restart" or t == 0 or not hit[t - 1][j])
                    if count == params.l and not done:
                        done = True
                        want.add((-1 if mode == "carry" else t, t * (m + 1) + j + 1, a, b))
    pairs = kernel.Collisions(hq, hx, present, limits, kind == "static")
    got = {(turn, key, a, b) for turn, key, bits in kernel.close_events(pairs, m, params.l, range(len(limits)), mode) for a, b in zip(*map(list, kernel.bit_places(bits)))}
    assert got == want and want
    if mode == "carry":  # a level on its own: what came before is one event
        level = 2
        own = {(key, a, b) for turn, key, bits in kernel.close_events(pairs, m, params.l, range(level, level + 1)) for a, b in zip(*map(list, kernel.bit_places(bits)))}
        end = (level - 1) * (m + 1) + m
        assert own == {(max(key, end), a, b) for _, key, a, b in want if key <= level * (m + 1) + m}


def answers(found):
    return sorted(map(tuple, found.result.collect())), sorted(map(tuple, found.stats.collect()))


def test_searches_do_not_depend_on_how_they_run(spark):
    family = Family("loose", 6, 500, 24.0)
    p, _ = scattered(spark, objects=40)
    q = p.where("object_id % 17 = 2")
    static = build_index(p, make_projections(family, derive_params("static", beta=25 / 60)), block_points=64)
    whole = answers(object_knn(static, q, family, (1, 2), 3, exclude_self=True))
    assert whole[0] and {s[1] for s in whole[1]} <= {"T1", "T2"} and all(r[0] != r[2] for r in whole[0])
    assert answers(object_knn(static, q, family, (1, 2), 3, mode="iterative", exclude_self=True)) == whole


def test_close_pairs_at_an_event_against_all_events():
    rng, m, threshold, limits = np.random.default_rng(4), 30, 16, [1, 2, 4, 8]
    hq, hx, known = rng.integers(-3, 3, (61, m)), rng.integers(-3, 3, (200, m)), rng.random((200, m)) < 0.9
    begins = np.array([0, 24, 32, 120, 168])
    ends = np.append(begins[1:], 200)
    entry = np.full((61, 200), 1 << 20)
    for _, key, bits in kernel.close_events(kernel.Collisions(hq, hx, known, limits, True), m, threshold, range(4)):
        entry[kernel.bit_places(bits)] = key
    at = kernel.CloseAt(hq, np.array([0, 20, 50]), limits, m, threshold)
    block = at.block(hx, known, begins, ends)
    some = block.some(np.array([0, 2, 3]))
    for key in range(4 * (m + 1)):
        for g, (a, b) in enumerate(at.groups):
            want = [int((entry[a:b, x:y] <= key).sum()) for x, y in zip(begins, ends)]
            assert block.counts(g, key).tolist() == want and some.counts(g, key).tolist() == [want[k] for k in (0, 2, 3)]
            assert some.some(np.array([1, 2])).counts(g, key).tolist() == [want[2], want[3]]


@pytest.mark.parametrize("chosen", [False, True])
def test_first_candidates_against_all_events(spark, chosen):
    family = Family("loose", 6, 500, 60.0)
    p, points = scattered(spark, objects=200)
    index = build_index(p, make_projections(family, derive_params("static", beta=25 / 200)), block_points=64)
    held = index.table.where("proj = 0").select("block", "hashes").collect()
    names = [o for r in held for o in np.frombuffer(bytes(r.hashes), np.int64).tolist()]
    assert sorted(names) == sorted(points) and len(held) >= 32  # every object lies whole in one block
    (q,) = kernel.query_batches(p.where("object_id IN (3, 40, 77)"))
    if chosen:
        sizes = index.sizes.where("object_id % 3 = 1")
        index = replace(index, sizes=sizes, n_objects=sizes.count())
    search = _Search(index, family, (1, 2), 3, (1, 5), "carry", "R", "distance", True, chosen)
    search.enough = 9
    rows = read_postings(index, index.proj.hashes(q.vec), search.top)
    every = {(r.q_obj, r.object_id): r.key for r in search.keys(rows, q, range(search.top + 1)).collect()}
    known = search.sampled_stops(rows, q)
    first = {(r.q_obj, r.object_id): r.key for r in search.first_keys(rows, q, known).collect()}
    assert first.items() <= every.items() and len(first) < len(every)
    for name in q.sizes():
        last = sorted(key for (o, _), key in every.items() if o == name)[8]
        assert known.get(name, last) >= last and {x for x in every if x[0] == name and every[x] <= last} <= first.keys()


def test_an_object_larger_than_a_block(spark):
    p = spark.createDataFrame([(o, 1000 * o + k, [k, o, 7]) for o, n in ((1, 30), (2, 150), (3, 49), (4, 5)) for k in range(n)], POINTS)
    index = build_index(p, make_projections(Family("hand", 3, 100), derive_params("static")), block_points=64)
    held = {}
    for r in index.table.where("proj = 0").collect():
        names, sizes = np.frombuffer(bytes(r.hashes), np.int64).tolist(), np.frombuffer(bytes(r.members), np.int64).reshape(2, -1)[1].tolist()
        assert len(names) == 1 or 2 not in names
        for o, n in zip(names, sizes):
            held.setdefault(o, []).append(n)
    assert {o: sum(n) for o, n in held.items()} == {1: 30, 2: 150, 3: 49, 4: 5} and sorted(map(len, held.values()))[-2:] != [4, 4]


def test_filtered_and_empty_searches(spark):
    family = Family("loose", 6, 500, 24.0)
    p, _ = scattered(spark, objects=60)
    index = build_index(p, make_projections(family, derive_params("static", beta=25 / 60)))
    q = p.where("object_id IN (4, 15)")
    some = spark.range(0, 60, 3).select(F.col("id").alias("object_id"))
    pre = object_knn(index, q, family, (1, 2), 4, where=some).result.collect()
    truth = gamma.exact_object_knn(p.join(some, "object_id", "left_semi"), q, family, (1, 2), 4).collect()
    assert {r.object_id for r in pre} <= set(range(0, 60, 3)) and len(pre) == len(truth) == 8
    post = object_knn(index, q, family, (1, 2), 4, where=some, filter_mode="post").result.collect()
    assert {r.object_id for r in post} <= set(range(0, 60, 3)) and len(post) <= 8
    none = object_knn(index, q.where("false"), family)
    assert none.result.count() == 0 and none.stats.count() == 0


def test_rings_read_every_posting_once(spark):
    p, q = family_points(spark, SF, "twin")
    index = build_index(p, projections("twin"))
    hashed = index.proj.hashes(next(kernel.query_batches(q)).vec)
    key = ["block", "proj", "bucket"]
    rings = [{tuple(r) for r in read_postings(index, hashed, t, t - 1 if t else None).select(*key).collect()} for t in range(4)]
    assert all(not (a & b) for k, a in enumerate(rings) for b in rings[:k])
    assert set().union(*rings) == {tuple(r) for r in read_postings(index, hashed, 3).select(*key).collect()}
    plan = read_postings(index, hashed, 1)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters" in plan and "GreaterThanOrEqual(bucket" in plan and "BroadcastHashJoin" in plan


def test_twins_are_found(spark):
    p, q = family_points(spark, SF, "twin")
    truth = {(r.q_obj, r.object_id) for r in gamma.exact_object_knn(p, q, TWIN, (1, 2), 2).collect()}
    assert truth == {(a, b) for a, o in ((8, 9), (98, 99), (23, 22), (77, 76), (17, 16), (80, 81)) for b in (a, o)}
    found = object_knn(build_index(p, projections("twin")), q, TWIN, (1, 2), 2)
    assert {(r.q_obj, r.object_id) for r in found.result.collect()} == truth
    for r in found.stats.collect():
        assert r.status in ("T1", "T2") and (r.status == "T2" or r.n_candidates >= 27)


def test_point_searches_against_plain_loops(spark):
    family = Family("loose", 6, 500, 60.0)
    p, own = scattered(spark, objects=30)
    q = p.where("object_id IN (3, 9)")
    rows = [(r.object_id, r.point_id, np.array(r.vec)) for r in p.collect()]
    got = {}
    for r in linear_knn(p, q, 7).collect():
        got.setdefault(r.q_id, []).append((r.rank, r.sq_dist, r.object_id, r.point_id))
    for o, i, v in rows:
        if o in (3, 9):
            best = sorted((int(((v - x) ** 2).sum()), a, b) for a, b, x in rows)[:7]
            assert sorted(got[i]) == [(k + 1, *x) for k, x in enumerate(best)]
    # with more close points allowed than there are, a hashed search ends by T2 or at the ladder's end with the nearest ones
    wide = hashed_knn(p, q, family, make_projections(family, derive_params("query", c=1.5, beta=0.5)), 7)
    assert {(r.q_id, r.rank) for r in wide.collect()} == {(i, k) for i in got for k in range(1, 8)}


@pytest.mark.parametrize("kind, c", [("static", 2), ("static", 3), ("query", 2), ("query", 1.5)])
def test_close_pairs_up_to_each_query_points_stop(kind, c):
    rng = np.random.default_rng(4)
    proj = make_projections(Family("kernel", 5, 700, 40.0), derive_params(kind, c=c, beta=0.3))
    q, x = rng.integers(-9000, 9000, (9, 5)), rng.integers(-9000, 9000, (300, 5))
    x[:9] = q + rng.integers(-300, 300, (9, 5))
    m, last = proj.params.m, proj.levels * (proj.params.m + 1) + proj.params.m
    near = ClosePairs(q, proj.hashes(q), proj)
    event = np.full((len(q), len(x)), last + 1)
    for _, key, bits in kernel.close_events(kernel.Collisions(proj.hashes(q), proj.hashes(x), None, proj.limits(), proj.static), m, proj.params.l, range(proj.levels + 1)):
        event[kernel.bit_places(bits)] = key
    stop = rng.integers(m, last + 1, len(q))
    want = {(a, b, int(event[a, b]), int(((q[a] - x[b]) ** 2).sum())) for a, b in zip(*np.nonzero(event <= stop[:, None]))}
    assert set(zip(*map(np.ndarray.tolist, near.block(x).pairs(stop)))) == want and want
    # a block's own bound holds enough pairs and ends few projections after the event that does; a task's is exact
    reached = near.block(x).reached(np.full(len(q), last), 40)
    exact = np.minimum(np.sort(event, axis=1)[:, 39], last)
    assert (reached >= exact).all() and (reached <= exact + 8).all()
    stops = Stops(len(q), 40, 301, last)
    for a in range(0, 300, 100):
        rows, _, keys, _ = near.block(x[a : a + 100]).pairs(stops.at)
        stops.add(rows, keys, keys)
    assert stops.at.tolist() == exact.tolist()


def test_one_pass_serves_several_k(spark):
    family = Family("loose", 6, 500, 60.0)
    p, _ = scattered(spark, objects=30)
    index = build_index(p, make_projections(family, derive_params("static", beta=0.5)))
    q = p.where("object_id IN (2, 5, 11)")
    found = object_knn_of(index, q, family, (1, 3), (1, 4, 9))
    for k, rows in found.items():
        assert sorted(map(tuple, rows.collect())) == sorted(map(tuple, object_knn(index, q, family, (1, 3), k).result.collect()))
    assert len(found) == 3


@pytest.mark.parametrize("kind", ["static", "query"])
def test_hashed_lists_of_several_k_are_those_of_each(spark, kind):
    family = Family("loose", 6, 500, 60.0)
    p, _ = scattered(spark, objects=30)
    q, proj = p.where("object_id IN (3, 9)"), make_projections(family, derive_params(kind, beta=0.5))
    every = hashed_lists(p, q, family, proj, (4, 20, 9), 0.02).collect()
    for k in (4, 9, 20):
        assert sorted(tuple(r)[1:] for r in every if r.k_prime == k) == sorted(map(tuple, hashed_knn(p, q, family, proj, k, 0.02).collect()))
    assert {r.k_prime for r in every} == {4, 9, 20}


def test_lists_go_on_over_blocks():
    rng = np.random.default_rng(2)
    q, x = rng.integers(-20, 20, (150, 3)), rng.integers(-20, 20, (3000, 3))
    obj, pid = rng.integers(0, 9, 3000), rng.permutation(3000)
    held = Nearest(q, 12)
    for a in range(0, 3000, 700):
        held.add(obj[a : a + 700], pid[a : a + 700], x[a : a + 700])
    got: dict = {}
    for columns in held.lists():
        for row, *found in zip(*(c.tolist() for c in columns)):
            got.setdefault(row, []).append(tuple(found))
    for k, v in enumerate(q):  # a task sends k' entries a query point, however many blocks it has; many ties
        assert got[k] == sorted(zip(((x - v) ** 2).sum(axis=1).tolist(), obj.tolist(), pid.tolist()))[:12]


def test_windows_of_a_real_ratio(spark):
    family = Family("loose", 6, 500, 60.0)
    p, _ = scattered(spark, objects=8)
    proj = make_projections(family, derive_params("query", c=1.5, beta=0.5))
    hits = {tuple(r) for r in window_hits(p, p.where("object_id = 2"), proj, 3).select("proj", "q_id", "point_id").collect()}
    rows = [(r.object_id, r.point_id, proj.hashes(np.array([r.vec]))[0]) for r in p.collect()]
    reach = math.floor(proj.width * 1.5**3)
    assert hits == {(j + 1, a, b) for o, a, x in rows if o == 2 for _, b, y in rows for j in range(proj.params.m) if 2 * abs(x[j] - y[j]) <= reach}


# buffers


def test_lru_and_per_bucket_hand_case():
    trace = pd.DataFrame({"level": 0, "proj": 1, "bucket": [1, 2, 1, 3, 2], "bytes": 1})
    lru = buffers.replay(trace, "lru", 2)
    assert (lru["hits"], lru["misses"]) == (1, 4)
    assert buffers.replay(trace, "per_bucket", 2)["misses"] == 3
    assert buffers.replay(trace, "frequency", 2)["misses"] <= 4
    assert math.isclose(buffers.io_ms(10, 1.56), 95.0)


def test_lru_hits_grow_with_the_buffer(spark):
    p, q = family_points(spark, SF, "twin")
    trace = buffers.access_trace(p, q.where("object_id = 8"), projections("twin"), levels=3).toPandas().sort_values("seq")
    hits = [buffers.replay(trace, "lru", size)["hits"] for size in (2000, 8000, 32000)]
    assert hits == sorted(hits)


def test_split_hand_case(spark):
    needs = [(1, 3, 1, name, low, 8, b, 1) for name, low in ((1, 0), (2, 2), (3, 5)) for b in range(low, low + 8)]
    df = spark.createDataFrame(needs, "q_obj long, level int, proj int, q_id long, low long, length long, bucket long, bytes long")
    rows = sorted({(r.start, r.q_id, r.split_id + 1) for r in buffers.sliced(df, 2).collect()})
    assert [f"{'ABC'[q - 1]}{s}" for _, q, s in rows] == ["A1", "B1", "A2", "C1", "B2", "C2"]


class PlainBuffer:
    """The eviction rule with lists, one page at a time."""

    def __init__(self, capacity, remaining, recent_frac=0.1, far_frac=0.5, use_frequency=True):
        self.capacity, self.left, self.held = capacity, dict(remaining), []
        self.options = recent_frac, far_frac, use_frequency

    def access(self, page, size):
        recent, far_frac, use = self.options
        self.left[page] = max(0, self.left.get(page, 0) - 1)
        if any(p == page for p, _ in self.held):
            return True, 0
        if size > self.capacity:
            return False, 0
        gone = 0
        while sum(s for _, s in self.held) + size > self.capacity:
            names = [p for p, _ in self.held]
            old = names[: len(names) - int(len(names) * recent)]
            far = {p: abs(p[1] - page[1]) if p[0] == page[0] else math.inf for p in old}
            limit = sorted(far.values())[int((len(old) - 1) * far_frac)]
            best = min((p for p in old if far[p] >= limit), key=lambda p: (self.left.get(p, 0) if use else 0, -far[p], names.index(p)))
            self.held = [x for x in self.held if x[0] != best]
            gone += 1
        self.held.append((page, size))
        return False, gone


@pytest.mark.parametrize("options", [{}, {"recent_frac": 0.0}, {"far_frac": 0.0}, {"use_frequency": False}])
def test_frequency_eviction_against_plain_lists(options):
    rng = np.random.default_rng(5)
    pages = [(int(a), int(b)) for a, b in zip(np.sort(rng.integers(1, 4, 1500)), rng.integers(0, 40, 1500))]
    size = {p: int(rng.integers(1, 9)) for p in pages}
    counts = {p: pages.count(p) for p in set(pages)}
    fast, plain = buffers.FrequencyBuffer(60, counts, **options), PlainBuffer(60, counts, **options)
    assert [fast.access(p, size[p]) for p in pages] == [plain.access(p, size[p]) for p in pages]


def test_reuse_distances_give_lru_hits(spark):
    rng = np.random.default_rng(6)
    trace = pd.DataFrame({"q_obj": 1, "seq": range(400), "level": 0, "proj": 1, "q_id": 1, "bucket": rng.integers(0, 30, 400), "bytes": 1, "split_id": 0})
    df = spark.createDataFrame(trace)
    for pages in (1, 5, 40):
        assert buffers.lru_by_reuse_distance(df, pages).first().hits == buffers.replay(trace, "lru", pages)["hits"]


def test_naive_strategies_differ_as_reported(spark):
    p, q = family_points(spark, SF, "twin")
    trace = buffers.access_trace(p, q.where("object_id IN (8, 23)"), projections("twin"), levels=3)
    lru, each = (buffers.simulate_buffer(trace, policy, 3_000).toPandas() for policy in ("lru", "per_bucket"))
    assert (each.io_ms.sum() < lru.io_ms.sum()) and (each.alg_cost.sum() > lru.alg_cost.sum())


def test_estimates_are_close_to_what_queries_need(spark):
    p, q = family_points(spark, SF, "twin")
    proj = projections("twin")
    sample = buffers.random_points(p, 400, TWIN.dim)
    estimate = buffers.estimated_frequency(p, sample, proj, q.count(), sample.count(), levels=3)
    exact = buffers.bucket_needs(p, q, proj, 3).groupBy("proj", "bucket").agg(F.count("*").alias("exact_freq"))
    errors = buffers.frequency_error(exact, estimate).toPandas()
    assert len(errors) == proj.params.m and errors["corr"].median() > 0.5
    box = buffers.random_points(p, 50, TWIN.dim, source="box")
    assert box.count() == 50 and buffers.estimated_frequency(p, box, proj, 72, 50, shape="equal_depth", levels=2).select("region").distinct().count() == 10


# guarantee, families


def test_guarantee_rates_reach_their_targets(spark):
    rows = workloads.guarantee_rates(spark, "/root/testdata/sf0.001", "supp", seeds=3).collect()
    assert rows and all(r.p1 is None or r.p1 >= r.p1_target for r in rows) and all(r.p2 for r in rows)
    assert all(r.near_rate is None or r.near_rate >= r.near_target - 0.05 for r in rows)


def test_guarantee_rates_cover_every_level_and_all_batches(spark, monkeypatch):
    # objects of one point on a line: the nearest two within the first radius, the widest beyond the eighth
    family = Family("line", 2, 100, 1000.0)
    p = spark.createDataFrame([(o, o, [x, 0]) for o, x in enumerate([0, 50, 400, 1_500, 6_000, 20_000])], POINTS)
    monkeypatch.setitem(workloads.FAMILIES, "line", family)
    monkeypatch.setitem(workloads.BETA, "line", 0.25)
    monkeypatch.setattr(workloads, "family_points", lambda *_: (p, p.where("object_id < 4")))
    whole = workloads.guarantee_rates(spark, "", "line", seeds=2).collect()
    assert sorted((r.seed, r.level) for r in whole) == [(s, t) for s in range(2) for t in range(10)]
    monkeypatch.setattr(workloads, "query_batches", lambda q: kernel.query_batches(q, 1))
    batched = workloads.guarantee_rates(spark, "", "line", seeds=2).collect()
    assert sorted(map(str, batched)) == sorted(map(str, whole))


@pytest.mark.parametrize("name", ["twin", "user", "doc", "supp", "emb"])
def test_method_grids_take_ten_query_objects(monkeypatch, name):
    asked = {}
    monkeypatch.setattr(workloads, "stored_index", lambda *_: type("Stored", (), {"points": None, "proj": None}))
    monkeypatch.setattr(workloads, "random_queries", lambda p, n: asked.setdefault("n", n) and 1 / 0)
    with pytest.raises(ZeroDivisionError):
        catalogue.queries()[f"method_grid_{name}"](None, "")
    assert asked == {"n": 10}


def test_validation(spark):
    df = spark.createDataFrame([(1, 1, [1, 2]), (1, 2, None), (None, 3, [1, 2]), (1, 4, [1])], POINTS)
    assert validate_points(df, 2, "drop").count() == 1
    with pytest.raises(ValueError):
        validate_points(df, 2)
    assert validate_points(df.where(F.lit(False)), 2).count() == 0


def test_point_ids_that_would_repeat_are_an_error(spark):
    text = spark.createDataFrame([(1, "\n" * 10_000 + "x" * 30)], "doc_id long, text string")
    with pytest.raises(Exception, match="too many parts"):
        text_points(text, "doc_id", F.col("text")).collect()


def test_wide_vectors_are_refused():
    with pytest.raises(ValueError):
        kernel.QuerySet(np.array([1]), np.array([1]), np.array([[1 << 27]]))


@pytest.mark.parametrize("k, share", [(2, (1, 3)), (25, (1, 4)), (1, (1, 1))])
def test_the_highest_stop_is_that_of_the_searches(spark, monkeypatch, k, share):
    p, _ = scattered(spark, objects=60)
    family = Family("loose", 6, 500, 60.0)
    proj, q = make_projections(family, derive_params("static", beta=0.25)), p.where("object_id % 6 = 1")
    index = build_index(p, proj)
    stops = [r.stop_level for r in object_knn(index, q, family, share, k).stats.collect()]
    assert search.highest_stop(p, q, family, proj, share, k) == max(stops)
    for name, value in {"PIECE": 5, "POINTS": 40, "FEW": 1, "SHARES": (2,)}.items():  # objects in pieces, small blocks, samples
        monkeypatch.setattr(search, name, value)
    assert search.highest_stop(p, q, family, proj, share, k) == max(stops)


def test_buckets_are_counted_by_batch(spark):
    p, _ = scattered(spark)
    proj = make_projections(Family("loose", 6, 500, 60.0), derive_params("static", beta=0.25))
    want = sorted((r.proj, r.bucket, r.n) for r in inverted(p, proj).groupBy("proj", "bucket").agg(F.count("*").alias("n")).collect())
    found = buffers.bucket_catalog(p, proj)
    assert sorted((r.proj, r.bucket, r.n_points) for r in found.collect()) == want
    assert "Generate" not in found._jdf.queryExecution().toString()  # no row a point and projection
    wide = np.array([[0, 5], [1 << 40, 5]])
    assert buffers.bucket_counts(wide).to_pydict() == {"proj": [1, 1, 2], "bucket": [0, 1 << 40, 5], "n": [1, 1, 2]}


def test_traces_are_made_where_they_are_replayed(spark):
    p, _ = scattered(spark, objects=60)
    proj, q = make_projections(Family("loose", 6, 500, 60.0), derive_params("static", beta=0.25)), p.where("object_id % 6 = 1")
    catalog = buffers.bucket_catalog(p, proj)
    pages = buffers.estimated_frequency(p, p.where("point_id % 7 = 0"), proj, 5, 40, levels=3).join(catalog, ["proj", "bucket"])
    capacity = int(0.1 * p.count() * proj.params.m * buffers.ENTRY_BYTES)
    replays = [
        buffers.Replay("lru", "lru", capacity, 1, "independent"),
        buffers.Replay("per_bucket", "per_bucket", capacity),
        buffers.Replay("estimated", "frequency", capacity, 10, estimate="est_freq", options=(("frequencies", "estimated"),)),
        buffers.Replay("exact", "frequency", capacity, 10, options=(("frequencies", "exact"), ("recent_frac", 0.0))),
    ]
    found = buffers.replayed_costs(q, pages.toPandas(), proj, 3, replays)
    want = []
    for r in replays:
        trace = buffers.access_trace(p, q, proj, r.n_splits, 3, r.schedule).join(pages.select("proj", "bucket", "est_freq"), ["proj", "bucket"])
        want += buffers.simulate_buffer(trace, r.policy, r.capacity, r.name, **dict(r.options)).collect()
    assert len(want) == 40 and sorted(map(tuple, found.collect())) == sorted(map(tuple, want))


def test_rates_are_summed_where_objects_are_whole(spark):
    p, own = scattered(spark, objects=30)
    family, params = Family("loose", 6, 500, 60.0), derive_params("static", beta=0.25)
    projs = [make_projections(family, params, seed=s) for s in (1, 2)]
    batch = next(kernel.query_batches(p.where("object_id < 3")))
    found = workloads.close_rates(p, batch, family, projs, [1, 3], (1, 4), (1, 5))
    assert found.count() == 2 * 2 * 3 and all(c not in found.columns for c in ("object_id", "point_id"))
    for r in found.collect():
        near_limit, far_limit = ((step * 2**r.level * 500) ** 2 for step in (1, 2))
        want = np.zeros(7, np.int64)
        for vec in own.values():
            q, proj = own[r.q_obj], projs[r.seed]
            d = ((q[:, None] - vec[None]) ** 2).sum(axis=2)
            hq, hx = (proj.hashes(v) // 2**r.level for v in (q, vec))
            close = (hq[:, None] == hx[None]).sum(axis=2) >= params.l
            dist = np.sort(d.ravel())[max(1, -(-d.size // 4)) - 1]
            candidate, high = close.sum() * 20 >= d.size * 4, close.sum() >= d.size * (0.25 + params.beta / 2)
            near, far = d <= near_limit, d > far_limit
            want += [dist <= near_limit and candidate, dist <= near_limit, high and dist > far_limit, near.sum(), (near & close).sum(), far.sum(), (far & close).sum()]
        assert [r[c] for c in workloads.RATES] == want.tolist()


def test_seeds_give_the_events_of_their_own_searches(spark):
    p, _ = scattered(spark, objects=60)
    family, params = Family("loose", 6, 500, 60.0), derive_params("static", beta=0.25)
    projs = [make_projections(family, params, seed=s) for s in (1, 2)]
    q = p.where("object_id % 20 = 1")
    batch = next(kernel.query_batches(q))
    found = workloads.seeded_keys(p, batch, projs, (1, 3), 4)
    one_task = workloads.seeded_keys(p.coalesce(1), batch, projs, (1, 3), 4).collect()
    for s, proj in enumerate(projs):
        index = build_index(p, proj)
        own = _Search(index, family, (1, 3), 1, (1, 5), "carry", "R", "distance", True)
        every = sorted((r.q_obj, r.key, r.object_id) for r in own.keys(read_postings(index, proj.hashes(batch.vec), proj.levels), batch, range(proj.levels + 1)).collect())
        for o in batch.sizes():
            mine = [row for row in every if row[0] == o]
            last = mine[:4][-1][1]
            for rows in (found.collect(), one_task):
                some = sorted((o, r.key, r.object_id) for r in rows if r.q_obj == o * 2 + s)
                assert [r for r in some if r[1] <= last] == [r for r in mine if r[1] <= last] and set(some) <= set(mine)


def test_a_share_of_the_objects_bounds_the_search_of_all(spark, monkeypatch):
    p, _ = scattered(spark, objects=120)
    family, params = Family("loose", 6, 500, 60.0), derive_params("static", beta=0.25)
    projs = [make_projections(family, params, seed=s) for s in (1, 2)]
    batch = next(kernel.query_batches(p.where("object_id % 40 = 1")))
    monkeypatch.setattr(workloads, "SHARE", 3)
    known = workloads.seeded_stops(p, workloads.object_sizes(p), batch, projs, (1, 3), 4)
    every = workloads.seeded_keys(p, batch, projs, (1, 3), 10_000).collect()
    bounded = workloads.seeded_keys(p, batch, projs, (1, 3), 4, known).collect()
    assert known and set(bounded) < set(every)
    for name in {r.q_obj for r in every}:
        keys = sorted(r.key for r in every if r.q_obj == name)
        assert known.get(name, keys[3]) >= keys[3]
        kept = sorted(r.key for r in bounded if r.q_obj == name)
        assert kept[:4] == keys[:4] and kept.count(keys[3]) == keys.count(keys[3]) and all(k <= known.get(name, k) for k in kept)


def test_first_events_by_one_pass_of_a_level():
    rng = np.random.default_rng(5)
    m, threshold, limits = 9, 5, [1, 2, 4, 8]
    hx, hq = rng.integers(0, 12, (120, m)), rng.integers(0, 12, (10, m))
    begins, ends = np.arange(0, 120, 8), np.arange(8, 128, 8)
    at = kernel.CloseAt(hq, np.array([0, 4]), limits, m, threshold)
    block = at.block(hx, None, begins, ends)
    need = rng.integers(1, 9, len(begins))
    for group, (a, b) in enumerate(at.groups):
        events = range(1, 4 * (m + 1))
        counts = np.array([block.counts(group, key) for key in events])
        last = events[-1]
        some = np.flatnonzero(counts[-1] >= need)
        want = {int(o): int(events[int((counts[:, o] >= need[o]).argmax())]) for o in some}
        want = {o: key + (1 if key % (m + 1) == 0 else 0) for o, key in want.items()}
        every = search.located(block.some(some), group, m, need[some], last, counts[-1][some])
        assert {int(some[o]): key for o, key, _ in every} == want
        assert all(n == counts[key - 1][some[o]] for o, key, n in every)
        few = search.located(block.some(some), group, m, need[some], last, counts[-1][some], 3)
        third = sorted(want.values())[2]
        assert {int(some[o]): key for o, key, _ in few} == {o: key for o, key in want.items() if key <= third}


def test_query_points_that_share_cells_are_counted_once(monkeypatch):
    rng = np.random.default_rng(6)
    hq = np.sort(rng.integers(0, 40, (64, 12)), axis=0)
    at = kernel.CloseAt(hq, np.array([0]), [1, 8, 64], 12, 7)
    block = at.block(rng.integers(0, 40, (64, 12)), None, np.array([0, 32]), np.array([32, 64]))
    took, bits = [], kernel.close_bits
    monkeypatch.setattr(kernel, "WORDS", 8)
    monkeypatch.setattr(kernel, "close_bits", lambda rows, shape, *rest: bits([took.append(shape[0]) or r for r in rows], shape, *rest))
    for level in (1, 2):
        took.clear()
        cells = (hq // 8**level)[:, None] == (block.hx.T // 8**level)[None]
        want = (cells.sum(axis=2) >= 7).reshape(64, 2, 32).sum(axis=(0, 2))
        assert block.counts(0, level * 13 + 12).tolist() == want.tolist()
        assert sum(took) < 64 * 12
    assert sum(took) == 12  # one cell holds all query points
