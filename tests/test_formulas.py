"""Worked values, properties and independent re-derivations of the local steps."""

import itertools
import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from indextrigger.functions.bursts import tail_values
from indextrigger.functions.text import porter
from indextrigger.params import ChainParams, GroupParams, TopicParams
from indextrigger.plans.chains import probe, score_of
from indextrigger.plans.events import agglomerate
from indextrigger.plans.groups import cluster_quality, grouping, spherical_kmeans
from indextrigger.plans.topics import greedy_topics


def exact_tail(n, total, p):
    return sum(math.comb(total, k) * p**k * (1 - p) ** (total - k) for k in range(n))


@pytest.mark.parametrize("tail,want", [("inclusive", 0.6875), ("strict", 0.3125), ("pmf", 0.375)])
def test_tail_values(tail, want):
    assert tail_values([2], [4], [0.5], tail)[0] == pytest.approx(want, abs=1e-12)


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 120), st.floats(0.001, 0.999), st.data())
def test_tail_properties(total, p, data):
    n = data.draw(st.integers(0, total))
    strict, inclusive, mass = (float(tail_values([n], [total], [p], t)[0]) for t in ("strict", "inclusive", "pmf"))
    assert strict == pytest.approx(exact_tail(n, total, p), abs=1e-9)
    assert 0 <= strict <= inclusive <= 1 and inclusive - strict == pytest.approx(mass, abs=1e-9)


def test_large_tail_stays_finite():
    got = tail_values([10_000, 10_300, 9_700], [1_000_000] * 3, [0.01] * 3, "strict")
    assert np.isfinite(got).all() and got[2] < got[0] < got[1] and 0.49 < got[0] < 0.51


@pytest.mark.parametrize("word,stem", [("caresses", "caress"), ("ponies", "poni"), ("agreed", "agre"), ("plastered", "plaster"), ("motoring", "motor"), ("conflated", "conflat"), ("hopping", "hop"), ("filing", "file"), ("happy", "happi"), ("relational", "relat"), ("vietnamization", "vietnam"), ("triplicate", "triplic"), ("hopeful", "hope"), ("revival", "reviv"), ("adjustment", "adjust"), ("adoption", "adopt"), ("probate", "probat"), ("controll", "control"), ("roll", "roll"), ("sky", "sky"), ("by", "by")])
def test_porter(word, stem):
    assert porter(word) == stem


def test_event_score_value():
    x, y = np.array([0.2, 0.4, 0.6]), np.array([0.1, 0.2, 0.3])
    sums = (x.sum(), (x * x).sum(), y.sum(), (y * y).sum(), (x * y).sum(), 3)
    assert score_of(sums) == pytest.approx(0.28)
    assert score_of((0.5, 0.25, 0.5, 0.25, 0.25, 1)) == 0.0


def brute_greedy(names, jac, rho, inf, params):
    """The same choice, each objective worked out from all pairs."""

    def value(members, cand=None):
        all_ = [*members, *([cand] if cand is not None else [])]
        pairs = list(itertools.combinations(all_, 2))
        j = sum(jac[a, b] for a, b in pairs) / len(pairs)
        r = sum(rho[a, b] for a, b in pairs) / len(pairs)
        impact = {"sum": sum(inf[m] for m in all_), "mean": sum(inf[m] for m in all_) / len(all_), "candidate": inf[all_[-1]], "off": 1.0}[params.influence]
        return j * r * impact

    free, out = set(range(len(names))), []
    while free:
        seed = min(free, key=lambda i: (-inf[i], i))
        free.remove(seed)
        members, best = [seed], -math.inf
        while free and len(members) < (params.max_topic_size or len(names)):
            able = [c for c in sorted(free) if any(jac[c, m] * rho[c, m] > params.min_link for m in members)]
            if not able:
                break
            pick = max(able, key=lambda c: (value(members, c), -c))
            if value(members, pick) <= (params.min_pair_objective if len(members) == 1 else best):
                break
            best = value(members, pick)
            members.append(pick)
            free.remove(pick)
        out.append(sorted(names[m] for m in members))
    return out


@pytest.mark.parametrize("influence", ["sum", "mean", "candidate", "off"])
@pytest.mark.parametrize("seed", range(4))
def test_greedy_against_recomputation(influence, seed):
    rng = np.random.default_rng(seed)
    n = 14
    jac, rho = (np.triu(rng.random((n, n)) * (rng.random((n, n)) < 0.5), 1) for _ in range(2))
    jac, rho = jac + jac.T, rho + rho.T
    inf = rng.random(n)
    params = TopicParams(influence=influence, max_topic_size=6)
    names = [f"w{i:02d}" for i in range(n)]
    got = greedy_topics(names, jac, rho, inf, params)
    assert [t["features"] for t in got] == brute_greedy(names, jac, rho, inf, params)
    assert sorted(w for t in got for w in t["features"]) == names
    scaled = greedy_topics(names, jac, rho, inf * 7, params)
    assert [t["features"] for t in scaled] == [t["features"] for t in got]


def test_kmeans_on_cosines_equals_raw_vectors():
    rng = np.random.default_rng(3)
    x = np.concatenate([rng.normal(c + 0.35, 0.05, (6, 5)) for c in (np.eye(5)[0], np.eye(5)[1], np.eye(5)[2])])
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    labels = spherical_kmeans(unit @ unit.T, 3)
    assert len({tuple(labels[i : i + 6]) for i in (0, 6, 12)}) == 3 and all(len(set(labels[i : i + 6])) == 1 for i in (0, 6, 12))
    for _ in range(5):
        centers = np.stack([unit[labels == c].sum(axis=0) for c in range(3)])
        again = (unit @ (centers / np.linalg.norm(centers, axis=1, keepdims=True)).T).argmax(axis=1)
    assert (again == labels).all()
    found, k, ratio = grouping(unit @ unit.T, GroupParams(merge_all_at=0.99))
    assert k == 3 and ratio == pytest.approx(cluster_quality(unit @ unit.T, found))


def test_grouping_edges():
    assert grouping(np.eye(1), GroupParams())[1] == 1
    assert grouping(np.full((4, 4), 0.9) + 0.1 * np.eye(4), GroupParams())[1] == 1
    labels, k, _ = grouping(np.array([[1, 0.8, 0], [0.8, 1, 0], [0, 0, 1.0]]), GroupParams(method="threshold"))
    assert k == 2 and labels[0] == labels[1] != labels[2]


def toy():
    groups = {(1, 0): [1], (2, 0): [1], (2, 1): [2], (3, 0): [1, 2], (4, 0): [1], (5, 0): [3]}
    rate = {(1, 1): 0.1, (1, 2): 0.3, (2, 2): 0.2, (1, 3): 0.9, (2, 3): 0.9, (1, 4): 0.8, (3, 5): 0.7}
    pvi = {0: 0.1, 1: 0.1, 2: 0.3, 3: 0.9, 4: 0.8, 5: 0.2}
    link = {((1, 0), (2, 0)): 1.0, ((2, 0), (3, 0)): 0.5, ((2, 1), (3, 0)): 0.05, ((3, 0), (4, 0)): 0.5, ((4, 0), (5, 0)): 0.0}
    fore, back = {}, {}
    for (a, b), v in link.items():
        fore.setdefault(b, {})[a[1]] = v
        back.setdefault(a, {})[b[1]] = v
    return groups, fore, back, rate, pvi


def test_probe_toy():
    chains = probe(*toy(), ChainParams(link_threshold=0.1))
    main = chains[0]
    assert main.seed == 3 and sorted(main.groups) == [(1, 0), (2, 0), (3, 0), (4, 0)]
    assert main.score > 0
    used = [g for c in chains for g in c.groups]
    assert len(used) == len(set(used)) == 6  # every group is in one chain
    for c in chains:
        wins = sorted({w for w, _ in c.groups})
        assert wins == list(range(wins[0], wins[-1] + 1))
    loose = probe(*toy(), ChainParams(link_threshold=0.0, require_gain=False))
    assert (2, 1) in loose[0].groups  # without the tests the weak link is followed
    fork = probe(*toy(), ChainParams(link_threshold=0.1, branching="fork"))
    assert all(len({w for w, _ in c.groups}) == len(c.groups) for c in fork)


def test_agglomerate_against_all_linkages():
    sim = np.array([[1, 0.9, 0.1], [0.9, 1, 0.6], [0.1, 0.6, 1.0]])
    assert list(agglomerate(3, sim, 0.5, "single")) == [0, 0, 0]
    assert list(agglomerate(3, sim, 0.5, "average")) == [0, 0, 2]
    assert list(agglomerate(3, sim, 0.5, "complete")) == [0, 0, 2]


@pytest.mark.parametrize("linkage", ["single", "average", "complete"])
def test_agglomerate_against_all_pairs_anew(linkage):
    """Kept bests of rows against a search of all pairs in every step, with many ties; rows are sought again only if they lost their best."""
    r = np.random.default_rng(4)
    for n in (0, 1, 2, 9, 30):
        sim = np.triu(np.round(r.random((n, n)) * 6) / 6 * (r.random((n, n)) < 0.6), 1)
        sim = sim + sim.T
        parts = {i: [i] for i in range(n)}
        near = lambda x, y: sim[np.ix_(parts[x], parts[y])]
        value = {"single": np.max, "average": np.mean, "complete": np.min}[linkage]
        while len(parts) > 1:
            best, _, i, j = max((round(float(value(near(x, y))), 12), (-x, -y), x, y) for x in parts for y in parts if x < y)
            if best < 0.5:
                break
            parts[i] += parts.pop(j)
        want = {k: i for i, own in parts.items() for k in own}
        assert list(agglomerate(n, sim, 0.5, linkage)) == [want[k] for k in range(n)]
