import math

import numpy as np
import pytest

from residual_marginals.lattice import Workload
from residual_marginals.operators import blocks, residuals
from residual_marginals.plans import planner
from residual_marginals.plans.privacy import BudgetExceeded, Ledger, delta_of, eps_to_rho, exp_select_local, rho_to_eps
from residual_marginals.plans.schedule import Schedule
from tests.test_transforms import domain_of

DOMAIN = domain_of((3, 4, 2))
PRIORS = [{}, {0: 50.0}, {0: 5.0, 1: 0.3, 3: 0.2}, {t: 1e6 for t in range(7)}]


@pytest.mark.parametrize("prior", PRIORS)
@pytest.mark.parametrize("rho", [1e-4, 0.5, 20.0])
def test_conditional_plan_is_optimal(prior, rho):
    plan = planner.conditional_plan(7, DOMAIN, prior, rho)
    left, gap = planner.plan_check(plan, rho)
    assert abs(left) < 1e-9 * max(1, rho) and gap < 1e-9
    assert math.isclose(planner.residual_rho(plan), rho, rel_tol=1e-9)
    rng = np.random.default_rng(0)
    p, v, a = (np.array([getattr(x, f) for x in plan]) for f in ("p", "v", "prior"))
    best = planner.plan_error(plan)
    draws = rng.dirichlet(np.full(len(plan), 0.5), 20_000) * 2 * rho / p
    with np.errstate(divide="ignore"):
        assert (v / (draws + a)).sum(axis=1).min() >= best * (1 - 1e-9)
    iid = planner.iid_plan(7, DOMAIN, rho)
    assert sum(x.v / (x.new + prior.get(x.tau, 0)) for x in iid) >= best * (1 - 1e-9)


def test_without_priors_the_plan_is_isotropic():
    for x, y in zip(planner.iid_plan(7, DOMAIN, 0.3), planner.conditional_plan(7, DOMAIN, {}, 0.3)):
        assert math.isclose(x.new, y.new, rel_tol=1e-12)
        assert math.isclose(x.sigma2, math.prod(DOMAIN.shape(7 & ~x.tau)) / 0.6, rel_tol=1e-12)


def test_numeric_plan_agrees():
    plan = planner.conditional_plan(7, DOMAIN, PRIORS[2], 0.5)
    numeric = planner.numeric_plan(plan, 0.5, 5000)
    got = sum(x.v / (n + x.prior) for x, n in zip(plan, numeric))
    assert planner.plan_error(plan) <= got <= planner.plan_error(plan) * 1.001


def test_pruning_stays_in_budget():
    full = planner.conditional_plan(7, DOMAIN, PRIORS[2], 0.5)
    for again in (True, False):
        cut = planner.conditional_plan(7, DOMAIN, PRIORS[2], 0.5, 0.2, again)
        assert planner.residual_rho(cut) <= 0.5 * (1 + 1e-12)
        assert sum(x.keep for x in cut) < len(cut)
        assert planner.plan_error(cut) <= planner.plan_error(full) * (1 + 0.5)


def test_single_length_axis_and_refusals():
    domain = domain_of((3, 1))
    assert [x.tau for x in planner.coefficients(3, domain)] == [0, 1]
    with pytest.raises(ValueError):
        planner.iid_plan(7, DOMAIN, 0)


def test_batch_plan_spends_all_and_beats_even_noise():
    w = Workload.all_kway(DOMAIN, 2)
    for objective in ("sum", "max"):
        plan = planner.batch_plan(w, DOMAIN, 0.5, objective=objective)
        assert math.isclose(planner.residual_rho(plan), 0.5, rel_tol=1e-9)
    known = {x.tau: x.new for x in planner.batch_plan(w, DOMAIN, 0.5)}
    even: dict[int, float] = {}
    for g in w.sets:
        for x in planner.iid_plan(g, DOMAIN, 0.5 / 3):
            even[x.tau] = even.get(x.tau, 0) + x.new
    error = lambda k: sum(planner.expected_mse(g, DOMAIN, k) for g in w.sets)
    assert error(known) <= error(even)
    worst = {x.tau: x.new for x in planner.batch_plan(w, DOMAIN, 0.5, objective="max")}
    top = lambda k: max(planner.expected_mse(g, DOMAIN, k) for g in w.sets)
    assert top(worst) <= top(known) * (1 + 1e-9)


def test_expected_errors_by_simulation():
    rng = np.random.default_rng(3)
    known = {t: 0.5 + t for t in range(8)}
    errors = []
    for _ in range(4000):
        noisy = {}
        for tau in range(8):
            draw = rng.normal(scale=known[tau] ** -0.5, size=DOMAIN.shape(tau))
            noisy[tau] = residuals.residual_of(draw, DOMAIN, tau, tau)
        errors.append(residuals.assemble(noisy, DOMAIN, 7))
    errors = np.array(errors)
    assert np.isclose((errors**2).mean(), planner.expected_mse(7, DOMAIN, known), rtol=0.03)
    assert np.isclose(np.abs(errors).sum(axis=(1, 2, 3)).mean(), planner.expected_l1(7, DOMAIN, known), rtol=0.03)
    assert planner.expected_sse(7, DOMAIN, known) == 24 * planner.expected_mse(7, DOMAIN, known)
    assert planner.expected_mse(7, DOMAIN, {0: 1.0}) == math.inf


def test_isotropic_noise_as_residual_noise():
    draws = np.random.default_rng(5).normal(size=(20_000, 3, 4))
    two = domain_of((3, 4))
    z = np.array([residuals.residual_of(d, two, 3, 1) for d in draws[:5000]])
    assert np.allclose(np.cov(z.T), 4 * (np.eye(2) + 1), atol=0.5)
    assert math.isclose(sum(x.p * x.new / 2 for x in planner.iid_plan(3, two, 0.5)), 0.5)


def test_weighted_norm_needs_no_inverse():
    v = np.kron(np.eye(2) + 1, np.eye(3) + 1)
    u = np.random.default_rng(1).normal(size=(2, 3))
    assert np.isclose(u.ravel() @ np.linalg.solve(v, u.ravel()), (blocks.center_all(u) ** 2).sum())


def test_conversions():
    assert round(eps_to_rho(1, 1e-9), 5) == 0.01497 and round(eps_to_rho(1, 1e-9, "simple"), 5) == 0.01178
    rhos = [0.001, 0.01, 0.1, 1, 5]
    tight = [rho_to_eps(r, 1e-9) for r in rhos]
    assert tight == sorted(tight)
    for r, e in zip(rhos, tight):
        assert e <= rho_to_eps(r, 1e-9, "simple") and math.isclose(eps_to_rho(e, 1e-9), r, rel_tol=1e-6) and delta_of(r, e) <= 1e-9 * 1.001


def test_ledger_refuses():
    ledger = Ledger(1.0)
    ledger.spend("a", 0.6)
    with pytest.raises(BudgetExceeded):
        ledger.spend("b", 0.5)
    ledger.spend("c", ledger.left)
    assert math.isclose(ledger.total, 1.0) and len(ledger.rows) == 2


def test_exponential_mechanism_frequencies():
    scores, eps = {k: float(k) for k in range(6)}, 1.0
    picks = np.bincount([exp_select_local(scores, eps, 1.0, b"s", str(k))[0] for k in range(6000)], minlength=6) / 6000
    want = np.exp(np.arange(6) * eps / 2)
    assert np.abs(picks - want / want.sum()).max() < 0.025


def test_schedule():
    s = Schedule.initial(0.5, 8)
    assert math.isclose(s.round_rho, 0.5 * 0.5 / 8)
    s.fit(1e-3)
    assert math.isclose(s.round_rho, 1e-3, rel_tol=1e-9)
    before = s.sigma
    assert s.anneal(0.0, 10) and s.sigma == before / 2
    assert not s.anneal(1e9, 10)
