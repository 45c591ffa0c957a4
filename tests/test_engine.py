import numpy as np
import pytest

from svengine.functions.gates import Circuit, Gate, simulate
from svengine.operators import chunks as C
from svengine.operators import measure as M
from svengine.operators import rows as R
from svengine.operators import states as S
from svengine.operators import tiers as T
from svengine.plans.cost import blocked_cost, totals
from svengine.plans.transpile import Plan, plan_blocks
from svengine.sources import workloads as W


def vector(df, n):
    p = df.toPandas()
    v = np.zeros(2**n, complex)
    v[p.idx] = p.re + 1j * p.im
    return v


def test_executors_agree(spark):
    c = W.brickwork(5, 2)
    want = simulate(c)
    z = C.Register(S.zero_state(spark, 5, 3, "chunks"), 5, 3)
    p = plan_blocks(c, 3)
    assert np.allclose(vector(C.rows_of(C.run_blocked(z, p)), 5), want)
    assert np.allclose(vector(R.run_rows(S.zero_state(spark, 5), p), 5), want)
    for s in C.STRATEGIES:
        assert np.allclose(vector(C.rows_of(C.run_baseline(z, c, s)), 5), want)


def test_blocks_have_no_exchange_on_rows(spark):
    df = S.zero_state(spark, 6).selectExpr("*", "shiftright(idx, 3) AS chunk").repartition("chunk")
    for k in range(3):
        df = R.apply_u3(df, k, 0.3, 0.2, 0.1, ("chunk",))
    assert df._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 1


def test_encoders_refuse_bad_tables(spark):
    t = spark.createDataFrame([(0, 0.0), (1, 0.0)], "k long, v double")
    with pytest.raises(ValueError):
        S.amplitude_encode(t, "k", "v", 2)
    t = spark.createDataFrame([(0, 1.0), (0, 2.0)], "k long, v double")
    with pytest.raises(ValueError):
        S.amplitude_encode(t, "k", "v", 2)
    with pytest.raises(ValueError):
        S.amplitude_encode(spark.createDataFrame([(9, 1.0)], "k long, v double"), "k", "v", 2)


def test_dense_index_and_sampling(spark):
    t = spark.createDataFrame([(i * 7 % 50, i) for i in range(50)], "a long, b long")
    got = S.dense_index(t, ["a"]).toPandas().sort_values("a")
    assert got.idx.tolist() == list(range(50))
    shots = M.sample_shots(S.uniform_state(spark, 4), 64, 2).toPandas()
    assert len(shots) == 64 and shots.outcome.between(0, 15).all()


def test_collapse_and_expectation(spark):
    bell = R.run_gates(S.zero_state(spark, 2), Circuit(2, (Gate("h", (0,)), Gate("cx", (0, 1)))))
    assert np.allclose(vector(M.collapse(bell, 0, 1), 2), [0, 0, 0, 1])
    assert abs(M.expect_pauli(bell, 0b11, 0).first()["value"] - 1) < 1e-12
    assert abs(M.expect_pauli(bell, 0, 0b11).first()["value"] - 1) < 1e-12


def test_tiers_agree_and_count(spark):
    c = W.quantum_volume(spark, "/root/testdata/sf0.001", 5, 1)
    want, p = simulate(c), plan_blocks(c, 3)
    z = C.Register(S.zero_state(spark, 5, 3, "chunks"), 5, 3, symmetric=True)
    a, moved = T.run_tiered(z, p, 1)
    assert np.allclose(vector(C.rows_of(a), 5), want)
    assert moved == {"sections": 2 * 3 * len(p.blocks), "exchanges": 2 * 3 * len(p.remaps)}
    b, moved = T.run_in_place(z, c, 1)
    assert np.allclose(vector(C.rows_of(b), 5), want)
    assert sum(moved.values()) == 2 * 3 * len(c.gates)


def test_a_run_goes_on_after_its_last_generation(spark, tmp_path):
    c = W.brickwork(6, 3)
    p, folder = plan_blocks(c, 3), f"file://{tmp_path}/run"
    z = C.Register(S.zero_state(spark, 6, 3, "chunks"), 6, 3)
    half = Plan(p.n, p.nc, p.sections[:3], p.start, p.sections[2].after)
    C.run_blocked(z, half, 1, folder, 1).df.count()
    assert len(list((tmp_path / "run").iterdir())) == 2  # older generations are deleted
    lost = C.Register(z.df.where("chunk < 0"), 6, 3)
    assert np.allclose(vector(C.rows_of(C.run_blocked(lost, p, 1, folder, 1)), 6), simulate(c))


@pytest.mark.parametrize("restore", [True, False])
@pytest.mark.parametrize("budget", [1, 2, 3])
def test_the_swap_budget_holds_everywhere(restore, budget):
    for c in (W.brickwork(12, 3), W.qft(12)):
        p = plan_blocks(c, 6, max_swaps=budget, restore_order=restore)
        assert max(len(r.swaps) for r in p.remaps) <= budget
        assert sorted(s.ord for x in p.sections for s in x.steps) == list(range(len(c.gates)))
        assert not restore or p.end == tuple(range(12))


def test_start_layout_costs_an_encoded_register_a_remap():
    p = plan_blocks(Circuit(5, (Gate("h", (1,)), Gate("cx", (1, 4)))), 3, restore_order=False)
    assert totals(blocked_cost(p, 2))["exchanges"] == 0 and totals(blocked_cost(p, 2, encoded=True))["exchanges"] == 1


def test_shots_follow_the_cumulative_mass(spark):
    r = np.random.default_rng(1)
    v = r.random(64) ** 3
    v /= np.sqrt((v**2).sum())
    state = spark.createDataFrame([(i, float(x), 0.0) for i, x in enumerate(v)], "idx long, re double, im double")
    w = np.floor(v**2 * 1e9 + 0.5001).astype(int)
    ends = np.cumsum(w)
    for nc in (2, 6):
        got = {x["shot"]: x["outcome"] for x in M.sample_shots(state, 500, nc).collect()}
        assert got == {s: int(np.searchsorted(ends, (s * 2654435761) % ends[-1], side="right")) for s in range(500)}
    assert abs(M.quantile(M.probabilities(state), "p", 0.5) - np.quantile(v**2, 0.5)) < 1e-15


def test_plans_join_shots_without_nested_loops(spark):
    plan = M.sample_shots(S.uniform_state(spark, 6), 64, 2)._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan


def test_volume_source_is_the_same_in_any_number_of_parts(spark):
    from svengine.sources import volumes

    spark.dataSource.register(volumes.VolumeCircuits)
    read = lambda **o: spark.read.format("volumecircuits").options(**o).load()
    rows = [sorted(map(str, read(n=5, depth=3, circuits=2, parts=p).collect())) for p in (1, 4, 50)]
    assert rows[0] == rows[1] == rows[2] and len(rows[0]) == 2 * 3 * 2 * 11
    assert read(n=5, depth=3, circuits=2, parts=4).rdd.getNumPartitions() == 4
    for empty in ({"n": 1}, {"depth": 0}, {"circuits": 0}):
        assert read(**{"n": 4, "depth": 2, "circuits": 1, **empty}).isEmpty()
