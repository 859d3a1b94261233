import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from residual_marginals import fixtures as fx
from residual_marginals.domain import Attribute, Domain
from residual_marginals.lattice import Workload, closure, cover_plan, subsets, touched
from residual_marginals.operators import blocks, residuals
from residual_marginals.operators.axisops import AxisProgram, Step

TABLE = np.array(fx.WORKED_TABLE, float)


def test_worked_example():
    age = TABLE.sum(axis=1)
    assert age.tolist() == [14, 19, 23, 44]
    assert blocks.decompose(TABLE, (0,)).ravel().tolist() == [5, 9, 30]
    assert blocks.decompose(TABLE, (1,)).ravel().tolist() == [1, 12]
    assert blocks.decompose(TABLE, (0, 1)).tolist() == [[4, 13], [-6, 6], [11, 13]]
    assert blocks.to_coords(TABLE).tolist() == [[100, 1, 12], [5, 4, 13], [9, -6, 6], [30, 11, 13]]


def domain_of(shape):
    return Domain([Attribute(f"a{k}", n, "0") for k, n in enumerate(shape)])


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(1, 4), min_size=0, max_size=4), st.integers(0, 10_000))
def test_round_trip_and_equal_forms(shape, seed):
    domain, array = domain_of(shape), np.random.default_rng(seed).normal(size=shape)
    whole = (1 << len(shape)) - 1
    assert np.allclose(blocks.from_coords(blocks.to_coords(array)), array)
    parts = residuals.split(array, domain, whole)
    total = np.zeros(shape)
    for tau in subsets(whole):
        keep = residuals.positions(domain, whole, tau)
        one = residuals.residual_of(array, domain, whole, tau)
        if one.size:
            assert np.allclose(parts[tau], one)
            component = residuals.component_of(one, domain, tau, whole)
            assert np.allclose(component, blocks.component_direct(array, keep))
            total += component
        factors = blocks.factors(tuple(shape), keep)
        assert np.allclose(blocks.kron_by_axis(array, factors).ravel(), one.ravel())
        assert np.allclose(blocks.kron_full(array, factors).ravel(), one.ravel())
        axes = [a.name for a in domain.attributes]
        program = AxisProgram.decompose(axes, tuple(shape), domain.names(tau))
        assert np.allclose(program.compile_block(array).ravel(), one.ravel())
        assert np.allclose(blocks.kron_by_axis(array, program.compile_kron()).ravel(), one.ravel())
    assert np.allclose(total, array)
    assert np.allclose(residuals.assemble(parts, domain, whole), array)


def test_superset_independence():
    domain, array = domain_of((3, 4, 2)), np.random.default_rng(1).normal(size=(3, 4, 2))
    want = residuals.residual_of(array, domain, 7, 2)
    assert np.allclose(residuals.residual_of(array.sum(axis=0), domain, 6, 2), want)
    assert np.allclose(residuals.residual_of(array.sum(axis=(0, 2)), domain, 2, 2), want)
    assert residuals.cheapest_source(2, [7, 6, 2], domain) == 2
    with pytest.raises(ValueError):
        residuals.cheapest_source(1, [2, 4], domain)
    with pytest.raises(ValueError):
        residuals.positions(domain, 2, 1)


def test_simplify_keeps_the_result():
    axes, shape = ["a", "b", "c"], (3, 4, 1)
    mixed = AxisProgram([Step("sub", "a"), Step("sum", "b"), Step("smear", "c", 1)], axes, shape)
    simple = mixed.simplify()
    assert [s.kind for s in simple.steps] == ["sum", "sub"]
    array = np.random.default_rng(2).normal(size=shape)
    assert np.allclose(simple.compile_block(array), mixed.compile_block(array))
    assert simple.op_count() < mixed.op_count()


def test_compilers_agree(spark):
    table = fx.worked(spark)
    for keep in ([], ["age"], ["educ"], ["age", "educ"]):
        program = AxisProgram.decompose(["age", "educ"], (4, 3), keep)
        got = {tuple(r[k] for k in keep): r["value"] for r in program.compile_cells(table).collect()}
        want = program.compile_block(TABLE)
        assert got == {tuple(i[("age", "educ").index(k)] for k in keep): v for i, v in np.ndenumerate(want)}
        back = AxisProgram.reconstruct(["age", "educ"], (4, 3), keep)
        cells = {(r["age"], r["educ"]): r["value"] for r in back.compile_cells(program.compile_cells(table)).collect()}
        assert all(abs(cells[i] - v) < 1e-9 for i, v in np.ndenumerate(back.compile_block(want)))


def test_workloads():
    domain = domain_of((3, 4, 2, 5))
    w = Workload.all_kway(domain, 2)
    assert len(w.sets) == 6 and len(w.closure()) == 11 and w.maximal() == w.sets
    assert closure([3]) == [0, 1, 2, 3]
    assert touched(0, w.sets) == 6 and touched(1, w.sets) == 3 and touched(3, w.sets) == 1
    assert len(Workload.with_target(domain, "a0", 2).sets) == 3
    for s in w.sets:
        assert any(c & s == s for c in cover_plan(w.sets, domain, 40))
    with pytest.raises(ValueError):
        Workload.all_kway(domain, 9)
    with pytest.raises(ValueError):
        Domain([Attribute("a", 1, "0"), Attribute("a", 2, "0")])
    with pytest.raises(ValueError):
        Attribute("a", 0, "0")
