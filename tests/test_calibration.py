import math
import statistics

import pytest

from veilstream.functions import accounting, calibrate, noise, tree
from veilstream.spec import TEST_SECRET, Budget, GateConfig, Measure, StreamSpec, Timing


def test_rho_goldens():
    assert calibrate.rho_of(3, 1e-9 / 3) == pytest.approx(0.11418, abs=2e-5)
    assert calibrate.rho_of(1, 1e-9) == pytest.approx(0.01497, abs=2e-5)


def test_delta_is_monotone():
    d = [calibrate.delta_of(r, 3) for r in (0.01, 0.05, 0.1, 0.3)]
    assert d == sorted(d) and d[0] < d[-1] <= 1


def test_node_sigma_of_the_long_tail_preset():
    p = calibrate.plan(StreamSpec(secret=TEST_SECRET, bound=32, timing=Timing(100)))
    assert p.sigma == pytest.approx(33.5, abs=0.1)
    assert min(p.taus) == pytest.approx(184, abs=2) and max(p.taus) == pytest.approx(505, abs=5)


def test_variance_peaks():
    for t, peak in ((100, 3.795), (150, 4.299), (1000, 5.302)):
        assert max(tree.variance(i) for i in range(1, t + 1)) == pytest.approx(peak, abs=1e-3)
    assert max(tree.variance(i, "plain") for i in range(1, 101)) == 6


def test_composition():
    assert accounting.compose_optimal(1, 1.0, 1e-9, 1.0) == pytest.approx(1e-9)
    e, d = accounting.compose_optimal_inverse(100, 6, 1e-9)
    assert e == pytest.approx(0.097, abs=0.01) and d == 1e-9 / 200
    assert e > 6 / 100  # better than basic
    assert accounting.compose_optimal(100, e, d, 6) <= 1e-9 * 1.01
    assert accounting.compose_inverse(10, 2, 1e-6, "basic") == (0.2, 1e-7)


def test_gate_delta_and_theorem_threshold():
    assert calibrate.gate_delta_total(1, 1e-9, 1e-12) == 1e-9 + (math.e + 1) * 1e-12
    a, b = calibrate.tau_theorem(100, 1e-9, 1, 1e-9), calibrate.tau_theorem(1000, 1e-9, 1, 1e-9)
    assert b > a > calibrate.tau_theorem(100, 1e-9, 3, 1e-9)


def test_equivalent_thresholds_fall_with_eps():
    x = [calibrate.equivalent_threshold(e, 1e-9, 150) for e in (1, 3, 10)]
    assert x == sorted(x, reverse=True)
    assert [round(v) for v in x] == [pytest.approx(114, abs=6), pytest.approx(42, abs=3), pytest.approx(16, abs=2)]


def test_analytic_gaussian_beats_the_classic_bound():
    assert calibrate.gaussian_sigma(0.5, 1e-6, 1) < calibrate.gaussian_sigma(0.5, 1e-6, 1, analytic=False)


@pytest.mark.parametrize("kind", ["plain", "bottom_up"])
def test_prefix_noise_equals_the_tree_object(kind):
    for t in (1, 2, 3, 5, 8, 16):
        p = tree.PrefixNoise("s", "x", "k", 3, kind, t)
        b = tree.BruteTree(t, lambda level, j: noise.normal("s", "x", "k", 3, level, j))
        exact = 0.0
        for i in range(1, t + 1):
            b.add(i - 1, i * 1.5)
            exact += i * 1.5
            assert b.prefix(i, kind) == pytest.approx(exact + p.at(i))


def test_noise_has_the_stated_variance():
    for i in (3, 7, 8):
        x = [tree.PrefixNoise("s", "x", str(k), triggers=8).at(i) for k in range(4000)]
        assert statistics.pstdev(x) == pytest.approx(math.sqrt(tree.variance(i)), rel=0.05)


def test_sqrt_factor_squares_to_prefix_sums():
    f = tree.sqrt_factor(6)
    assert all(sum(f[j] * f[i - j] for j in range(i + 1)) == pytest.approx(1) for i in range(6))


def test_ledger_charges_union_and_measures():
    spec = StreamSpec(secret=TEST_SECRET, bound=4, measures=(Measure("a"), Measure("b", "v", 5.0)), budget=Budget(2, 1e-8), gate=GateConfig(beta_union=False))
    rows = accounting.ledger_rows(spec)
    assert [r[0] for r in rows] == ["gate tree", "gate threshold", "value a", "value b", "total"]
    assert rows[1][3] == pytest.approx(8 * 1e-8 / 3, rel=1e-6)  # T times the share without the union


def test_discrete_noise_is_whole_and_has_its_variance():
    x = [noise.discrete_normal("s", "x", str(k), 1, 0, 0, 3.0) for k in range(4000)]
    assert all(isinstance(v, int) for v in x)
    assert abs(statistics.mean(x)) < 0.2 and statistics.pstdev(x) == pytest.approx(3.0, rel=0.05)
    draws = tree.discrete_draws("s", "x", "k", 1, 3.0)
    assert all((3.0 * v).is_integer() or abs(3.0 * v - round(3.0 * v)) < 1e-9 for v in tree.prefix_noise(8, "plain", draws))
    with pytest.raises(ValueError):
        GateConfig(noise="discrete")


def test_secrets_are_required_looked_up_late_and_never_printed(monkeypatch, tmp_path):
    with pytest.raises(TypeError):
        StreamSpec(bound=1)
    with pytest.raises(ValueError):
        noise.resolve(None)
    monkeypatch.setenv("NOISE_KEY", "from the environment")
    (tmp_path / "key").write_text("from a file\n")
    assert noise.resolve(noise.EnvSecret("NOISE_KEY")) == "from the environment" and noise.resolve(noise.FileSecret(str(tmp_path / "key"))) == "from a file"
    for secret in ("hidden text", noise.FixedSecret("hidden text")):
        assert "hidden" not in repr(StreamSpec(bound=1, secret=secret)) and "hidden" not in repr(secret if not isinstance(secret, str) else "")
