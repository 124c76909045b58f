import pytest

from linkedrank.functions.scoring import plain_score
from linkedrank.plans import families, networks, slots
from linkedrank.plans.catalog import LIBRARY, SAMPLE, SAMPLE_MATCHES, SAMPLE_STATS, TRADE


@pytest.mark.parametrize("matched, counts", [
    (["part", "supplier"], {4: 5, 5: 16, 6: 24, 7: 72}),
    (["part", "orders", "customer"], {4: 15, 5: 39, 6: 87}),
    (["part", "customer"], {4: 5, 5: 10, 6: 18}),
])
def test_trade_network_counts(matched, counts):
    for m, n in counts.items():
        assert len(networks.generate(TRADE, matched, m)) == n


def test_sample_and_library_counts():
    assert [len(networks.generate(SAMPLE, ["papers", "authors"], m)) for m in (4, 5)] == [3, 7]
    nets = networks.generate(LIBRARY, ["documents", "author"], 6)
    assert not any(rel == "labels" for n in nets for rel, _ in n.nodes)


def test_networks_are_sound_and_unique():
    nets = networks.generate(TRADE, ["part", "orders", "customer"], 6)
    assert len({n.code for n in nets}) == len(nets)
    assert all(networks.leaves_matched(n) and networks.respects_links(n) for n in nets)
    assert all(n.canonical().code == n.code for n in nets)


def scores(df_margin=0.0, avdl_margin=0.0):
    out = {}
    for row, (tf, dl) in SAMPLE_MATCHES.items():
        n, df, avdl = SAMPLE_STATS["papers" if row[0] == "p" else "authors"]
        out[row] = plain_score(tf, dl, n, df, avdl, df_margin, avdl_margin)
    return out


def test_worked_scores_and_ceilings():
    want = {"p1": 3.28, "p2": 7.04, "p5": 3.33, "a1": 4.00, "a3": 3.40, "a5": 3.36}
    assert {k: round(v, 2) for k, v in scores().items()} == want
    ceil = {"a1": 4.23, "a3": 3.64, "a5": 3.60, "p1": 3.52, "p2": 7.42, "p5": 3.57}
    assert all(abs(v - ceil[k]) < 0.0055 for k, v in scores(0.2, 0.1).items())


def test_worked_families():
    c = scores(0.2, 0.1)
    best = {"papers": max(c[r] for r in c if r[0] == "p"), "authors": max(c[r] for r in c if r[0] == "a")}
    nets = networks.generate(SAMPLE, ["papers", "authors"], 5)
    w = sorted(round(families.weight(n, best), 2) for n in nets)
    assert all(abs(a - b) < 0.011 for a, b in zip(w, sorted([5.15, 2.93, 5.39, 6.84, 5.32, 5.70, 3.03])))
    values = [families.weight(n, best) for n in nets]
    label, error = families.kmeans_1d(values, 2)
    assert abs(error - families.exact_error(values, 2)) < 1e-9
    low = {round(v, 2) for v, a in zip(values, label) if a == label[values.index(min(values))]}
    assert len(low) == 2 and max(low) < 3.1
    assert len(set(families.cluster(nets, best, 0.0).values())) == 1
    assert len(set(families.cluster(nets, best, 1.0).values())) == 7


def test_slot_graph_shares_and_bounds_depth():
    nets = networks.generate(TRADE, ["part", "orders", "customer"], 6)
    shared = slots.build(nets)
    alone = slots.build(nets, {n.code: i for i, n in enumerate(nets)})
    assert len(shared) < len(alone) <= sum(n.size for n in nets)
    assert all(s.depth <= 6 // 2 + 1 for s in shared.values())
