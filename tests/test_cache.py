"""The set-based cache against the sequential one, on random traces and on a worked example."""

import random
from collections import defaultdict

import pytest

from halograph.operators import cache, graph, partition, sampling
from halograph.operators.cache import CacheSpec
from halograph.operators.simulator import POLICIES, CacheTable
from halograph.plans.epoch import Partitioned, SampleConfig, plan_epoch

PUSH = "epoch int, sent_it int, arrive_it int, from_rank int, to_rank int, layer int, vid long"
ASK = "epoch int, rank int, it int, layer int, vid long"


def sequential(pushes, asks, spec, rounds, policy="oldest"):
    tables = defaultdict(lambda: CacheTable(spec.cs, spec.ls, policy=policy))
    out = {}
    for it in range(rounds):
        for key in {(r, k) for *_, r, k, _ in pushes} | {(r, k) for _, r, _, k, _ in asks}:
            tables[key].admit(it, [v for _, _, a, _, r, k, v in pushes if a == it and (r, k) == key])
            wanted = [v for _, r, i, k, v in asks if i == it and (r, k) == key]
            for v, w in zip(wanted, tables[key].probe(it, wanted)):
                w = w if it >= spec.d or spec.probe_in_warmup else None
                out[key[0], it, key[1], v] = w
    return out


@pytest.mark.parametrize("seed", range(6))
def test_plan_equals_simulation(spark, seed):
    rng = random.Random(seed)
    spec = CacheSpec(cs=rng.choice([1, 2, 3, 6, 0]), ls=rng.randint(0, 4), d=rng.randint(0, 3))
    rounds = 15
    pushes = sorted({(0, it, it + spec.d, 1 - r, r, k, rng.randrange(10)) for it in range(rounds - spec.d) for r in (0, 1) for k in (0, 1) for _ in range(rng.randint(0, 4))})
    asks = sorted({(0, r, it, k, rng.randrange(10)) for it in range(rounds) for r in (0, 1) for k in (0, 1) for _ in range(rng.randint(0, 6))})
    hits = cache.residency(spark.createDataFrame(asks, ASK), spark.createDataFrame(pushes, PUSH), spec, rounds)
    got = {(h["rank"], h["it"], h["layer"], h["vid"]): h["version_it"] if h["hit"] else None for h in hits.collect()}
    assert got == sequential(pushes, asks, spec, rounds)


def test_worked_refresh(spark):
    """Capacity two, writes a b a c: b is the victim, since a was refreshed."""
    pushes = [(0, t, t, 1, 0, 0, v) for t, v in ((1, 1), (2, 2), (3, 1), (4, 3))]
    asks = [(0, 0, 5, 0, v) for v in (1, 2, 3)]
    hits = cache.residency(spark.createDataFrame(asks, ASK), spark.createDataFrame(pushes, PUSH), CacheSpec(cs=2, ls=10, d=0), 6)
    assert {h["vid"]: h["hit"] for h in hits.collect()} == {1: True, 2: False, 3: True}


def test_two_triangles(spark):
    """Vertex 3 is sent in iterations 0 and 3 only: miss while warming up, hits of ages 0, 1, 2, then of age 0 again."""
    asks = spark.createDataFrame([(0, 0, it, 0, 3) for it in range(5)], ASK)
    sent = lambda its: spark.createDataFrame([(0, t, t + 1, 1, 0, 0, 3) for t in its], PUSH)
    spec = CacheSpec(cs=4, ls=2, d=1)
    got = lambda its: [(h["hit"], h["version_it"]) for h in sorted(cache.residency(asks, sent(its), spec, 5).collect(), key=lambda h: h["it"])]
    assert got([0, 3]) == [(False, None), (True, 1), (True, 1), (True, 1), (True, 4)]
    assert got([0])[4] == (False, None)


def test_triangle_structures(spark):
    pairs = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)]
    edges = graph.symmetric(spark.createDataFrame([(a, b, 1) for a, b in pairs] + [(1, 0, 1), (4, 4, 1)], "src long, dst long, w long"))
    assert edges.count() == 14  # a repeated edge adds weight, a self loop goes
    parts = spark.createDataFrame([(v, v // 3) for v in range(6)], "vid long, part int")
    pg = Partitioned.build(edges, parts, 2)
    assert {(r["part"], r["vid"]) for r in pg.halos.collect()} == {(0, 3), (1, 2)}
    assert {(r["owner"], r["vid"], r["remote"]) for r in pg.directory.collect()} == {(1, 3, 0), (0, 2, 1)}
    cat = {(r["part"], r["pid"]): (r["vid"], r["kind"]) for r in partition.catalog(parts, pg.halos, pg.placed).collect()}
    assert cat[0, 3] == (3, "halo") and cat[0, 0] == (0, "solid") and len(cat) == 8


@pytest.mark.parametrize("policy", POLICIES)
def test_policies_respect_capacity_and_life(policy):
    t = CacheTable(3, 2, policy=policy, degree={k: k for k in range(20)})
    rng = random.Random(1)
    for now in range(30):
        t.admit(now, rng.sample(range(20), 5))
        assert len(t.written) <= 3 and all(now - w <= 2 for w in t.written.values())
        t.probe(now, range(20))


def test_invariants_of_a_plan(work):
    plan, spec, pg = work.plan, work.spec, work.pg
    parts = {r["vid"]: r["part"] for r in work.parts.collect()}
    assert len(parts) == work.vertices.count()
    placed = defaultdict(set)
    for e in pg.placed.collect():
        placed[e["dst"]].add(e["src"])
    blocks = plan.blocks.collect()
    taken = defaultdict(set)
    for b in blocks:
        assert parts[b["dst"]] == b["rank"], "only solids are expanded"
        taken[b["epoch"], b["rank"], b["it"], b["layer"], b["dst"]].add(b["src"])
    for (*_, dst), got in taken.items():
        assert got <= placed[dst] and len(got) == min(3, len(placed[dst]))
    pushes = plan.push_plan.collect()
    per = defaultdict(int)
    for p in pushes:
        per[p["sent_it"], p["layer"], p["from_rank"], p["to_rank"]] += 1
        assert parts[p["vid"]] == p["from_rank"] != p["to_rank"] and p["arrive_it"] - p["sent_it"] == spec.d and p["sent_it"] < plan.rounds - spec.d
    assert max(per.values(), default=0) <= spec.nc
    for h in plan.hit_plan.where("hit").collect():
        assert 0 <= h["it"] - h["version_it"] <= spec.ls
    bid = defaultdict(list)
    for r in sampling.batch_ids(plan.frontier, plan.blocks).collect():
        bid[r["rank"], r["it"], r["layer"]].append(r["bid"])
    assert all(sorted(v) == list(range(len(v))) for v in bid.values())


def test_no_cache_no_hits(work):
    from dataclasses import replace

    for spec in (replace(work.spec, cs=0), replace(work.spec, nc=0), replace(work.spec, d=99)):
        assert work.hits(spec).where("hit").count() == 0


def test_one_rank_has_no_halos(spark, work):
    pg = Partitioned.build(work.edges, partition.by_hash(work.vertices, 1), 1)
    plan = plan_epoch(pg, work.train, SampleConfig((3, 3), 64), work.spec)
    assert plan.frontier.where("kind = 'halo'").count() == 0 and plan.push_plan.count() == 0


def test_hop_plan_limits_before_the_exchange(work):
    text = sampling.hop(work.plan.seeds, work.pg.placed, 3, 2)._jdf.queryExecution().toString()
    assert text.count("WindowGroupLimit") >= 2


def test_hub_samples_are_uniform(spark):
    """A star: each leaf should be drawn equally often over many seeds."""
    star = spark.createDataFrame([(k, 0, 1, 0, 0, 1) for k in range(1, 41)], "src long, dst long, w long, p_src int, p_dst int, deg_src long")
    seeds = spark.createDataFrame([(e, 0, it, 0) for e in range(20) for it in range(50)], "epoch int, rank int, it int, vid long")
    n = [r["count"] for r in sampling.hop(seeds, star, 4, 0).groupBy("src").count().collect()]
    assert len(n) == 40 and sum((x - 100) ** 2 / 100 for x in n) < 75  # chi-square, 39 degrees of freedom
