import warnings

import numpy as np
import pytest

from partnet.operators import compact
from partnet.plans import presets
from partnet.plans.graph import BottleneckSpec, Dag, Term, TradeOff, collapsed_terms, distortion_terms, update_rule

P2 = np.random.default_rng(1).dirichlet(np.ones(20)).reshape(5, 4)
P3 = np.random.default_rng(2).dirichlet(np.ones(24)).reshape(4, 3, 2)

SPECS = [
    (presets.single("A", "B"), P2),
    (presets.single("A", "B", target="b"), P2),
    (presets.single("A", "B", objective="gamma"), P2),
    (presets.parallel("A", "B"), P2),
    (presets.parallel("A", "B", objective="gamma"), P2),
    (presets.parallel("A", "B", 3), P2),
    (presets.symmetric("A", "B"), P2),
    (presets.symmetric("A", "B", "b"), P2),
    (presets.multi_target("A", ("B", "D")), P3),
    (presets.joint_source(("A", "B"), "D"), P3),
    (presets.custom(("A", "B"), "A->T1,T2", "T1->T2; T2->B"), P2),
    (presets.custom(("A", "B"), "A->T1,T2", "B->T2; T1->A"), P2),
]


def test_parse_and_order():
    dag = Dag.parse("A->T; T->B,C; D")
    assert dag.parents == {"A": (), "T": ("A",), "B": ("T",), "C": ("T",), "D": ()}
    assert dag.order().index("T") < dag.order().index("B")
    with pytest.raises(ValueError):
        Dag.parse("A->B; B->A")
    with pytest.raises(ValueError):
        Dag.parse("A->")


def test_spec_checks():
    with pytest.raises(ValueError):
        presets.custom(("A", "B"), "A->T; T->S", "T->B")
    with pytest.raises(ValueError):
        presets.custom(("A", "B"), "A->T", "T->Z")
    with warnings.catch_warnings(record=True) as seen:
        warnings.simplefilter("always")
        presets.custom(("A", "B"), "A->T", "A->T; T->B")
    assert seen
    spec = presets.symmetric("A", "B")
    assert BottleneckSpec.from_json(spec.to_json()) == spec


def test_trade_off():
    assert TradeOff.gamma(3).to_beta() == pytest.approx(0.75)
    assert TradeOff.beta(0.75).to_gamma() == pytest.approx(3)
    with pytest.raises(ValueError):
        TradeOff.beta(1.0).to_gamma()
    with pytest.raises(ValueError):
        TradeOff("beta", -1)
    assert presets.rescaled_trade("b", "beta", 0.5) == 1.0
    assert presets.rescaled_trade("a", "gamma", 3.0) == 0.75
    with pytest.raises(ValueError):
        presets.rescaled_trade("b", "beta", 1.5)


def test_terms_of_presets():
    spec = presets.symmetric("A", "B")
    assert [(t.y, t.z) for t in distortion_terms(spec, "TA")] == [(("A",), ()), (("TB",), ())]
    assert [(t.y, t.z, t.kind) for t in distortion_terms(spec, "TB")] == [(("B",), (), "child"), (("TA",), (), "own parents")]
    assert collapsed_terms(presets.parallel("A", "B", objective="gamma"), "T1") == [Term(("T2",), (), -1.0, "solved out"), Term(("B",), ("T2",))]
    assert update_rule(spec, "TA", TradeOff.gamma(4))[0] == 4
    assert update_rule(spec, "TA", TradeOff.gamma(4), "literal")[0] == pytest.approx(0.8)


@pytest.mark.parametrize("spec,p", SPECS, ids=lambda x: getattr(x, "name", ""))
@pytest.mark.parametrize("beta", [0.6, 1.7])
def test_stationarity(spec, p, beta):
    """The distortion rule gives the gradient of the objective, for every specification."""
    m = compact.random_tables(spec, p, dict.fromkeys(spec.clusters, 3), 3)
    assert max(compact.gradient_residual(m, t, TradeOff.beta(beta)) for t in spec.clusters) < 1e-7


@pytest.mark.parametrize("spec,p", SPECS[:8], ids=lambda x: getattr(x, "name", ""))
def test_descent(spec, p):
    """The objective never rises under asynchronous updates."""
    for trade in (0.5, 3.0, 10.0) if spec.objective == "gamma" or spec.name != "single_beta_b" else (0.3, 0.8):
        m = compact.random_tables(spec, p, dict.fromkeys(spec.clusters, 2), 5)
        run = compact.solve(m, TradeOff(spec.objective, trade), max_iter=150)
        assert run.max_rise < 1e-10


def test_second_objective_is_first_scaled():
    """With beta = gamma / (1 + gamma) the objectives differ by the factor 1 + gamma."""
    m = compact.random_tables(presets.symmetric("A", "B"), P2, {"TA": 3, "TB": 2}, 1)
    gamma = 4.0
    assert compact.objective(m, TradeOff.gamma(gamma)) == pytest.approx((1 + gamma) * compact.objective(m, TradeOff.beta(gamma / (1 + gamma))))


def test_collapsed_and_literal_share_fixed_points():
    spec = presets.symmetric("A", "B")
    m = compact.random_tables(spec, P2, {"TA": 2, "TB": 2}, 2)
    compact.solve(m, TradeOff.gamma(60.0), tol=1e-13, max_iter=3000)
    for t in spec.clusters:
        assert np.abs(compact.update(m, t, TradeOff.gamma(60.0), "literal") - m.q[t]).max() < 1e-6


def test_overlap_identity_dense():
    m = compact.random_tables(presets.parallel("A", "B"), P2, {"T1": 2, "T2": 3}, 0)
    both = compact.info(m, ("T1", "T2"), ("A",))
    assert both == pytest.approx(compact.info(m, ("T1",), ("A",)) + compact.info(m, ("T2",), ("A",)) - compact.info(m, ("T1",), ("T2",)), abs=1e-12)


def planted() -> np.ndarray:
    from partnet.workloads import LEVELS

    a, b = np.arange(80)[:, None], np.arange(20)[None, :]
    p = np.array(LEVELS, float)[a % 6, b % 3] * (1 + 0.05 * (((7 * a + 13 * b) % 5) - 2))
    return p / p.sum()


@pytest.mark.parametrize("noise,seed", [("uniform", 0), ("spectral", 0)])
def test_planted_splits(noise, seed):
    """2 x 2, 4 x 3, 6 x 3; then no split adds relevance; the clusters are the planted groups."""
    r = compact.anneal(presets.symmetric("a", "b"), planted(), compact.Schedule.geometric(5, 1.1, 330), noise=noise, seed=seed)
    sizes = [(x[3], y[3]) for x, y in zip(r.curve[0::2], r.curve[1::2], strict=True)]
    seen = list(dict.fromkeys(sizes))
    assert seen[:4] == [(1, 1), (2, 2), (4, 3), (6, 3)]
    for rows in (r.curve[0::2], r.curve[1::2]):
        assert all(b[5] >= a[5] - 1e-6 for a, b in zip(rows, rows[1:], strict=False))
    labels = r.model.q["TA"].argmax(axis=1)
    for g in range(6):
        assert len(set(labels[g::6])) == 1


def test_critical_weight():
    """A single bottleneck splits between 2.88 and 2.95, as predicted."""
    assert compact.critical_beta(planted()) == pytest.approx(2.894, abs=1e-3)
    r = compact.anneal(presets.single("a", "b"), planted(), compact.Schedule((2.8, 2.88, 2.95)), noise="spectral", max_k=2, max_iter=2000, tol=1e-9)
    assert [x[3] for x in r.curve] == [1, 1, 2]


def test_split_test_on_proportional_copies():
    q = np.array([[0.3, 0.1, 0.6], [0.6, 0.2, 0.2]])
    same = np.stack([q[:, 0], q[:, 1], 0.3 * q[:, 2], 0.7 * q[:, 2]], axis=1)
    gaps = compact.split_gaps(same, same.mean(axis=0))
    assert gaps[0] < 1e-12 and gaps[1] < 1e-12
    other = np.array([[0.3, 0.1], [0.1, 0.3]])
    assert compact.split_gaps(other, other.mean(axis=0))[0] == pytest.approx(0.25)


def test_zero_weight_and_one_cluster():
    spec = presets.single("A", "B")
    m = compact.random_tables(spec, P2, {"T": 3}, 0)
    q = compact.update(m, "T", TradeOff.beta(0.0))
    assert np.allclose(q, q[0])
    one = compact.random_tables(spec, P2, {"T": 1}, 0)
    assert np.allclose(compact.update(one, "T", TradeOff.beta(5.0)), 1)


def test_data_processing_bounds():
    m = compact.random_tables(presets.parallel("A", "B"), P2, {"T1": 2, "T2": 2}, 1)
    compact.solve(m, TradeOff.beta(8.0))
    whole = compact.info(m, ("A",), ("B",))
    both = compact.info(m, ("T1", "T2"), ("B",))
    assert max(compact.info(m, (t,), ("B",)) for t in ("T1", "T2")) <= both + 1e-12 <= whole + 1e-9


def test_best_hard_partition_by_exhaustion():
    """At a large weight the best of several starts reaches the best hard partition."""
    import itertools

    p = np.random.default_rng(5).dirichlet(np.ones(18) * 0.4).reshape(6, 3)
    spec = presets.single("A", "B")
    best = 0.0
    for labels in itertools.product(range(2), repeat=6):
        m = compact.Dense(spec, p, {"T": np.eye(2)[list(labels)]})
        best = max(best, compact.info(m, ("T",), ("B",)))
    found = 0.0
    for seed in range(20):
        m = compact.random_tables(spec, p, {"T": 2}, seed)
        compact.solve(m, TradeOff.beta(500.0))
        found = max(found, compact.info(m, ("T",), ("B",)))
    assert found >= best - 1e-3
