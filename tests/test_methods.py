"""Worked examples, counterexamples and invariants of the methods."""

from dataclasses import replace
from itertools import combinations
from math import exp

import pytest
from pyspark.sql import functions as F
from sitereach import model
from sitereach.operators import audience, certificates, influence, kvtree, policies, relevance, roads, selection, workloads
from sitereach.sources import keep

SF = "/root/testdata/sf0.001"


def pairs(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


@pytest.fixture(scope="module")
def city(spark):
    from sitereach.sources import keep

    return model.parts_city(spark, SF).kept(keep)


def tiny(spark, road, sites, terms, users, keys, visits=(), friends=()):
    both = [(a, b, n) for a, b, n in road] + [(b, a, n) for a, b, n in road]
    edges = [(a, b) for a, b in friends] + [(b, a) for a, b in friends]
    return model.City(
        pairs(spark, both, "src long, dst long, len long"), pairs(spark, sites, "poi long, v long, dis long"),
        pairs(spark, [(p, t, 1, 1000, w) for p, t, w in terms], "poi long, term string, tf long, idf_m long, w_m long"),
        pairs(spark, users, "usr long, v long, dis long"), pairs(spark, keys, "usr long, term string"),
        pairs(spark, list(visits), "poi long, usr long"), pairs(spark, edges, "usr long, friend long"), pairs(spark, [], "src long, dst long, indeg long"),
    )


def test_three_stores_reach_ten(spark):
    aud = pairs(spark, [(1, 1), (1, 2), (1, 3), (2, 3), (2, 4), (2, 5), (3, 6), (3, 7)], "poi long, usr long")
    social = pairs(spark, [(1, 8, 1), (2, 9, 1), (3, 10, 1), (4, 11, 1), (5, 12, 1)], "src long, dst long, indeg long")
    value = lambda sets: [float(influence.reachable(social, aud.where(F.col("poi").isin(s)).select("usr")).count()) for s in sets]
    assert selection.exhaustive([1, 2, 3], 2, value) == ([1, 2], 10.0)
    assert selection.greedy_local(social, aud, [1, 2, 3], 2) == ([1, 2], 10.0)


def test_size_is_not_reach(spark):
    aud = pairs(spark, [(1, 1), (1, 2), (1, 3), (2, 4), (2, 5)], "poi long, usr long")
    social = pairs(spark, [(4, 10 + i, 1) for i in range(5)], "src long, dst long, indeg long")
    assert policies.cardinality(aud, 1) == [1] == policies.cardinality_plain(aud, 1)
    assert selection.greedy_local(social, aud, [1, 2], 1)[0] == [2]


def test_two_hop_equals_worlds(spark):
    edges = [(1, 2, 0.5), (1, 3, 0.4), (2, 4, 0.3), (3, 4, 0.9), (1, 4, 0.2)]
    e = pairs(spark, edges, "src long, dst long, w double")
    seeds = pairs(spark, [(1,)], "usr long")
    exact = influence.worlds_exact(e, seeds).first()["influence"]
    local = influence.two_hop(e, seeds.select(F.lit(0).alias("set_id"), "usr")).first()["influence"]
    assert abs(exact - local) < 1e-9
    # monotone and submodular over all seed sets
    users = [1, 2, 3]
    subsets = [s for n in range(4) for s in combinations(users, n)]
    rows = [(i, u) for i, s in enumerate(subsets) for u in s]
    got = {r["set_id"]: r["influence"] for r in influence.two_hop(e, pairs(spark, rows, "set_id int, usr long")).collect()}
    f = {s: got.get(i, 0.0) for i, s in enumerate(subsets)}
    for a in subsets:
        for b in subsets:
            if set(a) <= set(b):
                assert f[a] <= f[b] + 1e-9
                for x in set(users) - set(b):
                    assert f[tuple(sorted({*a, x}))] - f[a] >= f[tuple(sorted({*b, x}))] - f[b] - 1e-9


def test_near_far_sets_and_modes(spark):
    samples = pairs(spark, [(0, 9, [1], [2]), (1, 9, [], [2]), (2, 9, [], []), (3, 9, [2], [1])], "rid long, target long, near array<long>, far array<long>")
    assert influence.coverage(samples, [1, 2], "inclusive") == 3  # counts a target that one is near to as remote, too
    assert influence.coverage(samples, [1, 2], "exclusive") == 1
    m = selection.Matrix(samples, [1, 2], 0, 4)
    assert [m.covered([1, 2], x) for x in ("any", "inclusive", "exclusive")] == [3, 3, 1]
    assert selection.lazy_cover(m, 1) == selection.greedy_matrix(m, 1)[0] == selection.greedy_cover(influence.hit_rows(samples), 1) == [2]
    assert selection.lazy_cover(m, 2) == selection.greedy_matrix(m, 2)[0]


def test_bounds():
    assert certificates.lower(0, 100, 10, 0.1) == pytest.approx(0, abs=1e-9)
    assert certificates.lower(50, 100, 100, 0.01) < 50 < certificates.upper(50, 100, 100, 0.01)
    p = certificates.plan(1500, 60, 5, 0.1, 1 / 1500, 472)
    assert p.rounds == 9 and round(p.theta_0) == 68
    assert pytest.approx(1 - exp(-1)) == certificates.GREEDY


def test_tie_member_is_kept(spark):
    # one place, without social part, exactly k-th in the geo-text list
    c = tiny(spark, [(1, 2, 3), (2, 3, 3)], [(1, 3, 1)], [(1, "tea", 1_000_000)], [(7, 1, 1)], [(7, "tea")])
    cand = pairs(spark, [(1,)], "poi long")
    assert [tuple(r) for r in audience.batch(c, cand, 1, 0.5, mode="none")[0].collect()] == [(1, 7)]
    assert audience.batch(c, cand, 1, 0.5, mode="none", tie_mode="strict_paper")[0].count() == 0


def test_short_lists_and_bare_users(spark):
    c = tiny(spark, [(1, 2, 3), (2, 3, 3)], [(1, 3, 1)], [(1, "tea", 500_000)], [(7, 1, 1), (8, 1, 1), (9, None, 1)], [(7, "tea"), (9, "tea")])
    got = [tuple(r) for r in relevance.top_k(c, 5, 0.5).select("usr", "poi", "rnk").collect()]
    assert got == [(7, 1, 1)]
    bounds = {r["usr"]: r["s_k"] for r in audience.user_lower_bounds(c, kvtree.k_nearest(c, 5), c.users, 5, 0.5).collect()}
    assert set(bounds.values()) == {0.0}


def test_colocated_places_touch(spark):
    c = tiny(spark, [(1, 2, 3)], [(1, 1, 1), (2, 1, 1)], [(1, "tea", 5), (2, "tea", 5)], [], [])
    assert [tuple(r) for r in kvtree.adjacency(c.road, kvtree.owners(c), c.sites, c.site_terms).collect()] == [("tea", 1, 2)]


def test_distances_agree(spark, city):
    few = city.sites.orderBy("poi").limit(5)
    a = {(r["src"], r["v"]): r["dist"] for r in roads.from_sources(city.road, few).collect()}
    label = roads.labels(city.road)
    ends = few.select(F.col("v").alias("a")).distinct().crossJoin(city.users.select(F.col("v").alias("b")))
    b = {(r["a"], r["b"]): r["dist"] for r in roads.label_distances(label, ends).collect()}
    assert a == b and all(d >= 0 for d in a.values())


@pytest.mark.parametrize("mode", ["class_dominance", "none"])
def test_batch_equals_brute(spark, city, mode):
    cand = workloads.drawn_sites(city, 12)
    want = set(map(tuple, audience.brute(city, cand, 5, 0.6).select("poi", "usr").collect()))
    got = audience.batch(city, cand, 5, 0.6, mode=mode, leaf_cap=12)[0]
    assert set(map(tuple, got.select("poi", "usr").collect())) == want


def _line(spark, sites, terms, keys):
    """Sixteen vertices in a row, a user at each (usr = 100 + v)."""
    return tiny(spark, [(v, v + 1, 2) for v in range(15)], sites, terms, [(100 + v, v, 1) for v in range(16)], keys)


def test_the_climb_ends_where_nobody_beyond_can_be_won(spark):
    # a weak place at vertex 0, strong ones at all others
    c = _line(spark, [(1, 0, 1)] + [(10 + v, v, 1) for v in range(1, 16)], [(1, "tea", 100_000)] + [(10 + v, "tea", 1_000_000) for v in range(1, 16)], [(100 + v, "tea") for v in range(16)])
    cand = pairs(spark, [(1,)], "poi long")
    want = set(map(tuple, audience.brute(c, cand, 2, 0.5).select("poi", "usr").collect()))
    got, counters = audience.batch(c, cand, 2, 0.5, leaf_cap=4)
    assert set(map(tuple, got.collect())) == want and counters["climbs_ended"] == 1 and counters["user_bounds"] < 16
    same, more = audience.batch(c, cand, 2, 0.5, leaf_cap=4, rules=audience.RULES - {"node"})
    assert set(map(tuple, same.collect())) == want and "climbs_ended" not in more and more["tested_classes"] >= 1


def test_the_climb_goes_on_for_keywords_held_only_beyond(spark):
    # nobody in the candidate's leaf wants tea, the users farthest away do
    c = _line(spark, [(1, 0, 1), (2, 0, 1)], [(1, "tea", 100_000), (2, "milk", 1_000_000)], [(100 + v, "milk") for v in range(4)] + [(115, "tea"), (114, "tea")])
    cand = pairs(spark, [(1,)], "poi long")
    got, counters = audience.batch(c, cand, 1, 0.5, leaf_cap=4)
    assert set(map(tuple, got.collect())) == {(1, 115), (1, 114)} and counters["climbs_ended"] == 0


def test_literal_border_test_loses_a_user(spark):
    # at the border the weak place near it wins, for the user far behind the border the strong place does
    c = tiny(spark, [(0, 1, 1), (1, 2, 1), (2, 3, 10), (3, 4, 10)], [(1, 0, 1), (2, 0, 9)], [(1, "tea", 100_000), (2, "tea", 300_000)], [(7, 4, 1)], [(7, "tea")])
    cand = pairs(spark, [(2,)], "poi long")
    sound = audience.batch(c, cand, 1, 0.0, leaf_cap=1)[0]
    literal = audience.batch(c, cand, 1, 0.0, leaf_cap=1, mode="border_paper")[0]
    assert [tuple(r) for r in sound.collect()] == [(2, 7)] and literal.count() == 0


def test_baseline_equals_brute_and_counts_alike(spark, city):
    cand = workloads.drawn_sites(city, 4)
    want = set(map(tuple, audience.brute(city, cand, 5, 0.6).select("poi", "usr").collect()))
    one, a = audience.combined(city, cand, 5, 0.6, 12)
    all_, b = audience.combined(city, cand, 5, 0.6, 12, one_by_one=False)
    assert set(map(tuple, one.collect())) == set(map(tuple, all_.collect())) == want and a == b and a["node_bounds"] > 4


def test_lists_list_no_pairs(spark, city, monkeypatch):
    pairs_of = relevance.relevant_pairs
    want = {(a, k): sorted(map(tuple, relevance.ranked(city, pairs_of(city, a), k).collect())) for a, k in ((0.6, 4), (1.0, 300))}

    def none(*_):
        raise AssertionError("pairs of users and places are listed")

    monkeypatch.setattr(relevance, "relevant_pairs", none)
    for (a, k), rows in want.items():
        assert sorted(map(tuple, relevance.top_k(city, k, a).collect())) == rows
    few = city.users.where("usr % 7 = 0")
    assert sorted(map(tuple, relevance.top_k(city, 4, 0.6, users=few).collect())) == [r for r in want[0.6, 4] if r[0] % 7 == 0]


def test_walked_bounds_are_bounds(spark, city):
    users = city.users.where("usr % 9 = 0")
    owner = kvtree.owners(city)
    lists = {r["usr"]: r["score"] for r in relevance.top_k(city, 3, 0.6).where("rnk = 3").collect()}
    got = audience.user_lower_bounds_walked(city, owner, kvtree.adjacency(city.road, owner, city.sites, city.site_terms), users, 3, 0.6).collect()
    assert len(got) == users.count() and all(r["s_k"] <= lists.get(r["usr"], 0.0) + 1e-12 for r in got) and any(r["s_k"] > 0 for r in got)


def test_lower_bounds_are_below(spark, city):
    lists = {r["usr"]: r["score"] for r in relevance.top_k(city, 5, 0.6).where("rnk = 5").collect()}
    for r in audience.user_lower_bounds(city, kvtree.k_nearest(city, 5), city.users, 5, 0.6).collect():
        assert r["s_k"] <= lists.get(r["usr"], 0.0) + 1e-12


def test_walkers_agree(spark, city):
    cand = workloads.drawn_sites(city, 6)
    aud = audience.brute(city, cand, 5, 0.6)
    users = city.users.select("usr")
    a = influence.reverse_samples(city.social, aud, users, 0, 20, coins="md5").orderBy("rid").collect()
    b = influence.reverse_samples_shuffled(city.social, aud, users, 0, 20).orderBy("rid").collect()
    assert [(r["target"], r["near"], r["far"]) for r in a] == [(r["target"], r["near"], r["far"]) for r in b]


def test_solvers_certify(spark, city):
    cand = workloads.drawn_sites(city, 5)
    h = selection.hybrid_approx(city, cand, 2, 5, 0.6, eps=0.3)
    assert len(h.sites) == 2 and h.certified is not None and h.certified_by in ("ratio", "theta_max")
    e = selection.local_heuristic(city, cand, 2, 5, 0.6, batches=2)
    assert len(e.sites) == 2 and e.certified >= certificates.GREEDY


def test_solvers_are_registered_over_the_whole_job(spark, city, monkeypatch):
    from sitereach.plans import registry

    seen = []

    def record(_, candidates, b, k, alpha, eps=0.1, x=200, samples=4096, **options):
        seen.append((candidates.count(), b, k, alpha, eps, x, samples))
        return []

    for module, solver in ((selection, "sampling_baseline"), (selection, "hybrid_approx"), (selection, "local_heuristic"), (policies, "influencers")):
        monkeypatch.setattr(module, solver, record)
    monkeypatch.setattr(registry, "_kept_city", lambda *_: city)
    monkeypatch.setattr(registry, "_result", lambda *_: None)
    monkeypatch.setattr(registry, "_sites", lambda *_: None)
    for name in ("select_baseline", "select_hybrid", "select_heuristic", "policy_influencer"):
        registry.QUERIES[name](spark, SF)
    assert seen == [(60, 5, 20, 0.6, 0.1, 200, 4096)] * 4


def test_whole_audience_equals_brute(spark, city, monkeypatch):
    from sitereach.plans import registry

    monkeypatch.setattr(registry, "_kept_city", lambda *_: city)
    _, cand, aud = registry._whole_audience(spark, SF)
    assert cand.count() == 60
    want = set(map(tuple, audience.brute(city, cand, 20, 0.6).select("poi", "usr").collect()))
    assert set(map(tuple, aud.collect())) == want
    # greedy over the sets of walkers, counted in Python
    rows = registry.influence.reverse_samples(city.social, aud, city.users.select("usr"), 0, 200, coins="md5").collect()
    left, chosen = [{*r["near"], *r["far"]} for r in rows], []
    for _ in range(5):
        chosen.append(max(sorted({p for s in left for p in s}), key=lambda p: sum(p in s for s in left)))
        left = [s for s in left if chosen[-1] not in s]
    hits = influence.hit_rows(spark.createDataFrame(rows, "rid long, target long, near array<long>, far array<long>"))
    assert selection.greedy_cover(hits, 5) == chosen


def test_baseline_goes_on_until_certified(monkeypatch):
    drawn = []

    class All:
        def __init__(self, samples, candidates, first, count):
            self.candidates, self.count = candidates, 0
            self.extend(samples, first, count)

        def extend(self, samples, first, count):
            drawn.append((first, count))
            self.count += count

        def covered(self, sites, mode="any"):
            return self.count if sites else 0

        def gains(self, sites, mode):
            return [0.0 if sites else float(self.count) for p in self.candidates if p not in sites]

    class Nobody:
        def __init__(self, *_, **__):
            pass

        def draw(self, first, count):
            return None

    monkeypatch.setattr(selection, "_pois", lambda c: [1, 2])
    monkeypatch.setattr(selection, "_setup", lambda *_: (None, None, None, 10))
    monkeypatch.setattr(selection.influence, "Walker", Nobody)
    monkeypatch.setattr(selection, "Matrix", All)
    monkeypatch.setattr(selection.cert, "lower", lambda c, n, size, d: 10.0 if size >= 1 << 22 else 0.0)
    got = selection.sampling_baseline(None, None, 1)
    assert got.certified_by == "ratio" and got.samples == 1 << 23
    # every sample is drawn once
    mine = sorted(x for x in drawn if x[0] < selection.SAMPLE_RANGES[1])
    assert all(a + n == b for (a, n), (b, _) in zip(mine, mine[1:], strict=False)) and sum(n for _, n in mine) == 1 << 22


def test_collections_grow(spark, monkeypatch):
    social = pairs(spark, [(i, (3 * i + j) % 40, 4) for i in range(40) for j in range(4)], "src long, dst long, indeg long")
    aud = pairs(spark, [(p, u) for p in range(5) for u in range(p, 40, 7)], "poi long, usr long")
    users = pairs(spark, [(i,) for i in range(40)], "usr long")
    walker = influence.Walker(social, aud, users, coins="md5")
    a = selection.Collection(walker, list(range(5)), 0, 13)
    a.double()
    monkeypatch.setattr(influence, "EDGE_LIMIT", 1)
    monkeypatch.setattr(influence, "NUMBER_LIMIT", 1)
    joined = influence.Walker(social, aud, users, coins="md5")
    assert not joined.small
    monkeypatch.setattr(selection, "MATRIX_BYTES", 1)
    b = selection.Collection(joined, list(range(5)), 0, 26)
    assert isinstance(b.found, selection.Counted) and a.found.count == b.found.count == 26
    for sites in ([], [1], [0, 3], [2, 4, 1]):
        for mode in ("any", "exclusive", "inclusive"):
            assert a.found.covered(sites, mode) == b.found.covered(sites, mode)
            assert a.found.gains(sites, mode) == b.found.gains(sites, mode)


def test_counts_answer_as_bitmaps_do(spark):
    samples = pairs(spark, [(0, 9, [1], [2]), (1, 9, [], [2]), (2, 9, [], []), (3, 9, [2], [1]), (4, 9, [3], [])], "rid long, target long, near array<long>, far array<long>")
    a, b = selection.Matrix(samples, [1, 2, 3], 0, 5), selection.Counted(samples, [1, 2, 3], 0, 5)
    assert selection.greedy_matrix(a, 2) == selection.greedy_matrix(b, 2)


def test_large_roads_go_by_joins(spark, monkeypatch):
    road = pairs(spark, [(1, 2, 3), (2, 1, 3), (2, 3, 4), (3, 2, 4)], "src long, dst long, len long")
    sources, ends = pairs(spark, [(1,), (3,), (99,)], "v long"), pairs(spark, [(1, 3), (2, 2), (1, 99), (99, 99)], "a long, b long")
    both = lambda: (sorted(map(tuple, roads.from_sources(road, sources).collect())), sorted(map(tuple, roads.between(road, ends).collect())))
    want = both()
    monkeypatch.setattr(roads, "ROAD_LIMIT", 1)
    assert both() == want and want[1] == [(1, 3, 7), (2, 2, 0)]


def _as_its_sql(spark, name, at):
    import __spark_entry__
    import duckdb

    con = duckdb.connect()
    for t in ("customer", "orders", "lineitem", "part"):
        con.execute(f"create view {t} as select * from '{at}/{t}.parquet'")
    want = con.execute(__spark_entry__.oracle_sql()[name])
    columns = [d[0] for d in want.description]
    got = sorted(map(tuple, __spark_entry__.queries()[name](spark, at).select(*columns).collect()))
    assert got == sorted(want.fetchall())
    return got


@pytest.mark.parametrize("name", ["node_terms", "tree_members", "tree_classes", "tree_borders"])
def test_tree_queries_follow_their_sql_at_any_size(spark, name):
    # leaves of 100 vertices would need one level here, the SQL builds two
    _as_its_sql(spark, name, SF)


@pytest.mark.parametrize("name", ["bounds_plan", "bounds_values"])
def test_bounds_follow_the_given_tables(spark, name):
    assert _as_its_sql(spark, name, SF) != _as_its_sql(spark, name, SF.replace("0.001", "0.01"))


def _street(spark, n=400, side=20):
    rows = [(v, t, 1 + (v * 7 + t) % 5) for v in range(n) for t in ([v + 1] if v % side < side - 1 else []) + ([v + side] if v + side < n else [])]
    return pairs(spark, rows + [(b, a, d) for a, b, d in rows], "src long, dst long, len long")


def test_searches_by_buckets_equal_searches_by_heap(spark):
    road, far = _street(spark), pairs(spark, [(0, 999, 100_000), (999, 0, 100_000)], "src long, dst long, len long")
    starts = pairs(spark, [(0,), (57,), (399,)], "v long")
    ends = starts.select(F.col("v").alias("a")).crossJoin(pairs(spark, [(3,), (58,), (398,)], "b long"))
    # one long street makes the lengths unfit for buckets, and shortens no way
    for f in (lambda r: roads.from_sources(r, starts).where("v <> 999"), lambda r: roads.between(r, ends)):
        assert sorted(map(tuple, f(road).collect())) == sorted(map(tuple, f(road.union(far)).collect()))
    sites = [(p, (p * 37) % 400, p % 3) for p in range(60)]
    near = []
    for r in (road, road.union(far)):
        c = tiny(spark, [], sites, [(p, "tea" if p % 2 else "ale", 1) for p, _, _ in sites], [], [])
        c = model.City(r, c.sites, c.site_terms, c.users, c.user_terms, c.checkins, c.friends, c.social)
        near.append(sorted(map(tuple, kvtree.k_nearest(c, 4).where("v <> 999").collect())))
        some = kvtree.k_nearest(c, 4, at=pairs(spark, [("tea", 5), ("ale", 399)], "term string, v long"))
        assert sorted(map(tuple, some.collect())) == [x for x in near[-1] if x[:2] in (("tea", 5), ("ale", 399))]
    assert near[0] == near[1] and len(near[0]) == 2 * 4 * 400


def test_what_a_search_finds_is_not_broadcast(spark):
    road, starts = _street(spark), pairs(spark, [(0,), (57,)], "v long")
    c = tiny(spark, [], [(1, 0, 1)], [(1, "tea", 1)], [], [])
    c = model.City(road, c.sites, c.site_terms, c.users, c.user_terms, c.checkins, c.friends, c.social)
    at = pairs(spark, [(v,) for v in range(400)], "v long")
    for found in (roads.from_sources(road, starts), kvtree.k_nearest(c, 2)):
        plan = found.join(at, "v")._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_large_relations_are_not_broadcast(spark, monkeypatch):
    from sitereach.sources import keep

    monkeypatch.setattr(model, "MERGE_ROWS", 2)
    c = tiny(spark, [(1, 2, 3)], [(p, 1, 1) for p in range(9)], [(p, "tea", 1) for p in range(9)], [(7, 1, 1)], [(7, "tea")]).kept(keep, "sites", "users")
    plan = lambda df: df.join(c.site_terms, "poi")._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" not in plan(c.sites) and keep(c.sites, "again") is c.sites
    assert not c.users._jdf.queryExecution().analyzed().toString().startswith("ResolvedHint")


@pytest.mark.parametrize("length", ["long", "double"])
def test_searches_end_at_a_radius(spark, city, length, monkeypatch):
    c = replace(city, road=city.road.withColumn("len", F.col("len").cast(length)))
    cand = workloads.drawn_sites(c, 5)
    every = {tuple(r) for r in roads.site_distances(c, cand).where("dist <= 40").collect()}
    assert every and {tuple(r) for r in roads.site_distances(c, cand, 40).collect()} == every
    found = roads.from_sources(c.road, c.sites.join(cand, "poi"), 30)
    assert found.agg(F.max("dist")).first()[0] <= 30
    monkeypatch.setattr(roads, "ROAD_LIMIT", 10)
    assert {tuple(r) for r in roads.site_distances(c, cand, 40).collect()} == every


def test_ranges_list_no_pairs(spark, city, monkeypatch):
    at, depth = kvtree.partition(city.road, depth=2)
    border = kvtree.borders(city.road, at, depth)
    got = {tuple(r) for r in kvtree.ranges(city, at, border, depth).collect()}
    plain = replace(city, road=city.road.withColumn("len", F.col("len").cast("double")))
    assert {tuple(r) for r in kvtree.ranges(plain, at, border, depth).collect()} == got
    listed, between = [], roads.between
    monkeypatch.setattr(roads, "between", lambda road, pairs: listed.append(1) or between(road, pairs))
    assert {tuple(r) for r in kvtree.ranges(city, at, border, depth).collect()} == got and not listed
    monkeypatch.setattr(roads, "ROAD_LIMIT", 10)
    assert {tuple(r) for r in kvtree.ranges(city, at, border, depth).collect()} == got and listed


def test_the_walkers_graph_does_not_pass_through_the_driver(spark, city, monkeypatch):
    aud = audience.brute(city, workloads.drawn_sites(city, 5), 10, 0.6)
    want = influence.reverse_samples_shuffled(city.social, aud, city.users.select("usr"), 0, 20).orderBy("rid").collect()
    from pyspark.sql.classic.dataframe import DataFrame

    def never(self):
        raise AssertionError("the graph is collected")

    monkeypatch.setattr(DataFrame, "toPandas", never)
    assert influence.reverse_samples(city.social, aud, city.users.select("usr"), 0, 20, coins="md5").orderBy("rid").collect() == want


@pytest.mark.parametrize("min_df", [0, 5])
def test_bounds_around_users_need_no_diagrams(spark, city, monkeypatch, min_df):
    rare = kvtree.split_terms(city.site_terms, min_df)[1] if min_df else None
    want = {tuple(r) for r in audience.user_lower_bounds(city, kvtree.k_nearest(city, 4, min_df), city.users, 5, 0.6, rare).collect()}
    with monkeypatch.context() as m:
        m.setattr(kvtree, "k_nearest", lambda *a: pytest.fail("diagrams are built"))
        assert {tuple(r) for r in audience.bounds_around(city, city.users, 5, 0.6, 4, min_df).collect()} == want
    monkeypatch.setattr(relevance, "PLACE_LIMIT", 10)
    assert {tuple(r) for r in audience.bounds_around(city, city.users, 5, 0.6, 4, min_df).collect()} == want


def test_the_index_holds_nearest_places_of_borders_only(spark, city):
    c, tree = kvtree.build(city, 3)
    border = tree.border.select("v").distinct()
    assert tree.nearest.join(border, "v", "left_anti").isEmpty()
    want = kvtree.k_nearest(c, 4).join(border, "v", "left_semi")
    assert {tuple(r) for r in tree.nearest.select("term", "v", "poi", "dist").collect()} == {tuple(r) for r in want.select("term", "v", "poi", "dist").collect()}


def test_what_a_batch_shares_is_not_broadcast(spark, city):
    c, tree = kvtree.build(city, 3)
    search = audience.open_search(c, tree, workloads.drawn_sites(c, 5), 3, "class_dominance")
    for df, key in ((search.to_site, "poi"), (search.keys, "poi")):
        plan = c.sites.select("poi").join(df, key)._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "BroadcastHashJoin" not in plan


def test_the_baseline_builds_what_it_reads_only(spark, city, monkeypatch):
    def no(*_, **__):
        raise AssertionError("not read by the baseline")

    monkeypatch.setattr(kvtree, "k_nearest", no)
    monkeypatch.setattr(kvtree, "ranges", no)
    monkeypatch.setattr(kvtree, "class_sets", no)
    cand = workloads.drawn_sites(city, 6)
    got, counters = audience.combined(city, cand, 5, 0.6, 12, one_by_one=False)
    assert set(map(tuple, got.collect())) == set(map(tuple, audience.brute(city, cand, 5, 0.6).collect()))
    few, index = audience.build_combined(city, 5, 0.6, 12, cand)
    assert {r["poi"] for r in index.matrix.select("poi").distinct().collect()} <= {r["poi"] for r in cand.collect()}
    assert counters["node_bounds"] > 0 and counters["unpruned_pairs"] <= counters["user_bounds"]


def test_a_list_is_done_once_k_places_beat_the_floor():
    import numpy as np

    # two places of one keyword, at vertices 0 and 1 of a road of two
    places = relevance.Places(np.array([1, 2, 1, 2]), np.array([-1, -1, 0, 0]), np.array([0, 1, 1000000, 1000000]), np.array([1, 1, 0, 0]))
    places.on(roads.Rows(np.array([0, 1]), np.array([1, 0]), np.array([500, 500])))
    hit, made = np.zeros(1, bool), []
    for floor in (None, 0.5, 0.2):
        made.append(relevance._List(places, hit, np.array([0]), np.zeros(0, np.int64), np.zeros(0), 2, 1, (0.0, 1.0), floor))
        made[-1].meet(np.array([0]), np.array([0.0]), hit)
    # its place scores 1/3, as another one beyond might: only a place of score 0.2 is known to be beaten
    assert [m.done(0.0) for m in made] == [False, False, True]


def test_packed_tables_are_passed_on_once(spark, city):
    c = city.kept(keep)
    assert roads.broadcast_rows(c.road) is roads.broadcast_rows(c.road) and relevance._placed(c)[1] is relevance._placed(c)[1]


def test_a_far_class_is_settled_at_one_border(spark):
    from types import SimpleNamespace

    nearest = pairs(spark, [("tea", 10, 2, 1)], "term string, v long, poi long, dist long")
    keys = pairs(spark, [(2, {"tea": 100})], "poi long, keys map<string,long>")
    # users are within 5 of border 10 and the candidate is 1000 beyond it: its way over border 11 is no shorter
    seen = pairs(spark, [(1, "0", 10, 1000, 1, 5, 1, 1), (1, "0", 11, 2000, 1, 5, 1, 2), (3, "0", 10, 3, 1, 5, 1, 1), (3, "0", 11, 4, 1, 5, 1, 2)], "poi long, node string, b long, d_p long, lo long, hi long, least long, nth int")
    rows = pairs(spark, [(p, "0", "tea", ["tea"], 100) for p in (1, 3)], "poi long, node string, cls string, terms array<string>, a long")
    for mode, want, tested in (("class_dominance", {1}, 1), ("border_paper", set(), 2)):
        s = audience.Search(None, SimpleNamespace(nearest=nearest), 1, mode, None, keys, None, seen)
        assert {r["poi"] for r in audience.beaten(s, rows).collect()} == want and s.counters["tested_borders"] == tested


def test_the_batch_builds_what_its_rules_read(spark, city, monkeypatch):
    cand, bounds = workloads.drawn_sites(city, 5), audience.bounds_around
    want = set(map(tuple, audience.brute(city, cand, 5, 0.6).collect()))

    def no(*_, **__):
        raise AssertionError("not read")

    monkeypatch.setattr(audience, "bounds_around", no)
    assert set(map(tuple, audience.batch(city, cand, 5, 0.6, rules=frozenset({"pseudo", "node"}), leaf_cap=12)[0].collect())) == want
    monkeypatch.setattr(audience, "bounds_around", bounds)
    for name in ("k_nearest", "ranges", "holders", "borders"):
        monkeypatch.setattr(kvtree, name, no)
    assert set(map(tuple, audience.batch(city, cand, 5, 0.6, mode="none", leaf_cap=12)[0].collect())) == want


def test_ranges_of_large_nodes_are_put_together_from_cells(spark, city, monkeypatch):
    # with vertices that nothing leads to, two of them without users
    far = pairs(spark, [(900, 901, 3), (901, 900, 3), (901, 902, 2), (902, 901, 2)], "src long, dst long, len long")
    c = replace(city, road=city.road.union(far), users=city.users.union(pairs(spark, [(900, 900, 2), (901, 900, 7)], "usr long, v long, dis long"))).kept(keep, "road", "users")
    at, depth = kvtree.partition(c.road, depth=2)
    border = keep(kvtree.borders(c.road, at, depth), "border")
    want = {tuple(r) for r in kvtree.ranges(c, at, border, depth).collect()}
    made, gathered = [], roads.gathered
    monkeypatch.setattr(roads, "gathered", lambda df, kind, *x: made.append(kind) or gathered(df, kind, *x))
    monkeypatch.setattr(kvtree, "TOGETHER", 7)
    for cap, cells in ((4, True), (2, True), (900, False)):
        monkeypatch.setattr(kvtree, "CELL", cap)
        assert {tuple(r) for r in kvtree.ranges(c, at, border, depth).collect()} == want and (kvtree._Tables in made) == cells
        made.clear()


def test_ways_over_cells_are_the_shortest():
    import numpy as np

    draw = np.random.default_rng(3)
    a, b = draw.integers(0, 60, (2, 90))
    length = draw.integers(1, 9, 90)
    rows = roads.Rows(np.r_[a, b, 60], np.r_[b, a, 61], np.r_[length, length, 4])
    cells = roads.Cells(rows, rows.ids // 30, 5)
    tables = [cells.inside(c)[:, np.searchsorted(cells.own(c), cells.border[cells.first[c] : cells.first[c + 1]])] for c in range(cells.count)]
    want = rows.distances(cells.border)
    for lo, hi in ((0, cells.count), (2, 3)):
        got = cells.between(tables, cells.border, lo, hi)[cells.first[lo] : cells.first[hi]]
        want_ = want[:, cells.border[cells.first[lo] : cells.first[hi]]].T
        assert (np.where(got == cells.NONE, -1, got) == want_).all()


def test_a_class_is_not_settled_at_one_border_without_a_range(spark):
    from types import SimpleNamespace

    # the place next to border 10 is far from users next to border 11, from where the candidate is the nearer one
    nearest = pairs(spark, [("tea", 10, 2, 1), ("tea", 11, 2, 5000)], "term string, v long, poi long, dist long")
    keys = pairs(spark, [(2, {"tea": 100})], "poi long, keys map<string,long>")
    seen = pairs(spark, [(1, "0", 10, 1000, 1, None, 1, 1), (1, "0", 11, 2000, 1, None, 1, 2)], "poi long, node string, b long, d_p long, lo long, hi long, least long, nth int")
    rows = pairs(spark, [(1, "0", "tea", ["tea"], 100)], "poi long, node string, cls string, terms array<string>, a long")
    s = audience.Search(None, SimpleNamespace(nearest=nearest), 1, "class_dominance", None, keys, None, seen)
    assert audience.beaten(s, rows).isEmpty() and s.counters["tested_borders"] == 1


def test_a_batch_looks_up_what_lies_around_the_borders_it_tests(spark, city, monkeypatch):
    cand = keep(workloads.drawn_sites(city, 5), "cand")
    c, tree = kvtree.build(city, 3, 12)
    for mode, outside in (("border_paper", False), ("class_dominance", True)):
        listed, looked = (audience.open_search(c, t, cand, 3, mode) for t in (tree, replace(tree, nearest=None, ranges=None)))
        index = audience._class_index(listed).where("node <> ''").select("node", "cls", F.col("terms").alias("set"))
        some = listed.own.select("poi", "terms").crossJoin(F.broadcast(index)).where(F.size(F.array_except("set", "terms")) == 0)
        rows = audience._weighed(listed, some.select("poi", "node", "cls"))
        want = {tuple(r) for r in audience.beaten(listed, rows, outside).collect()}
        assert want and {tuple(r) for r in audience.beaten(looked, rows, outside).collect()} == want

    def no(*_, **__):
        raise AssertionError("places nearest to all borders are listed")

    asked, ranges = [], kvtree.ranges
    monkeypatch.setattr(kvtree, "k_nearest", no)
    monkeypatch.setattr(kvtree, "ranges", lambda city, member, border, *x: asked.append(border.count()) or ranges(city, member, border, *x))
    got = audience.batch(city, cand, 3, 0.6, leaf_cap=12, rules=audience.RULES - {"node"})[0]
    assert set(map(tuple, got.collect())) == set(map(tuple, audience.brute(city, cand, 3, 0.6).collect()))
    assert asked and max(asked) < tree.border.count()
