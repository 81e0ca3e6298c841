"""The submatrix methods, merging, baselines, observables and dynamics against dense solvers and plain versions."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from nearfield.functions.elements import ElementModel
from nearfield.functions.kernels import MatFn, Purification
from nearfield.operators import baselines, combine, dynamics, generate, lattice, matrix, observables, patterns, potential, workloads
from nearfield.operators.submatrix import entries_of, locality_report, metrics_of, paired_purify, submatrix_apply
from nearfield.plans import balance
from nearfield.sources.tables import cut

SMALL = "/root/testdata/sf0.001"
MU = -0.275


def rows(spark, a, ids=None):
    a = np.asarray(a, float)
    ids = range(len(a)) if ids is None else ids
    return spark.createDataFrame([(int(i), int(j), float(a[p, q])) for p, i in enumerate(ids) for q, j in enumerate(ids) if a[p, q] != 0], matrix.MAT)


def to_dense(df, n):
    out = np.zeros((n, n))
    for r in df.collect():
        out[r.row, r.col] = r.val
    return out


def banded(n, seed=0, width=2):
    draw = np.random.default_rng(seed)
    a = draw.normal(size=(n, n)) * (np.abs(np.subtract.outer(range(n), range(n))) <= width)
    return (a + a.T) / 2


@pytest.fixture(scope="module")
def water(spark):
    a, box = workloads.water(spark, SMALL)
    a = cut(a)
    pair = cut(lattice.matrix_from_atoms(a, box, ElementModel()))
    ids, d, w = baselines.dense_density(pair, MU)
    _, h = baselines.dense(pair, value="h")
    _, s = baselines.dense(pair, value="s")
    return a, box, pair, h, s, d, w


# ---- sparse algebra


def test_algebra_is_numpy_s(spark):
    a, b = banded(12, 1), banded(12, 2, 3)
    x, y = rows(spark, a), rows(spark, b)
    assert np.allclose(to_dense(matrix.multiply(x, y), 12), a @ b)
    assert np.allclose(to_dense(matrix.multiply_blocks(matrix.blocks_of(x, 4), matrix.blocks_of(y, 4), 4), 12), a @ b)
    assert np.allclose(to_dense(matrix.axpy(2.0, x, -1.0, y), 12), 2 * a - b)
    assert np.allclose(to_dense(matrix.hadamard(x, y), 12), a * b)
    assert matrix.trace(x) == pytest.approx(np.trace(a)) and matrix.trace_of_product(x, y) == pytest.approx(np.trace(a @ b))
    n = matrix.norms(x)
    assert n["one"] == pytest.approx(np.abs(a).sum(0).max()) and n["fro"] == pytest.approx(np.linalg.norm(a))
    d = matrix.difference(x, y).first()
    on = a != 0
    assert d.max_abs == pytest.approx(np.abs((a - b)[on]).max()) and d.off_pattern == pytest.approx(np.sqrt((b[~on] ** 2).sum()))


def test_contract_of_a_matrix(spark):
    make = lambda r: spark.createDataFrame(r, matrix.MAT)
    for bad in ([(0, 0, None)], [(0, 0, float("nan"))], [(0, None, 1.0)], [(0, 0, 1.0), (0, 0, 2.0)], [(0, 1, 1.0)]):
        with pytest.raises(matrix.MatrixError):
            matrix.validate(make(bad))
    assert matrix.validate(make([(0, 1, 1.0)]), "union").count() == 2
    assert matrix.from_coo(make([(0, 0, 1.0), (0, 0, 2.0)])).first().val == 3.0
    assert matrix.with_diagonal(make([(0, 1, 1.0)])).count() == 3
    with pytest.raises(matrix.MatrixError):
        baselines.dense(spark.range(20).selectExpr("id as row", "id as col", "1.0D as val"), max_dim=10)


# ---- the submatrix method


def plain_submatrix(a, fn, groups):
    out = np.zeros_like(a)
    for own in groups:
        idx = np.flatnonzero((a[:, own] != 0).any(axis=1) | np.isin(range(len(a)), own))
        f = fn(a[np.ix_(idx, idx)])
        for j in own:
            out[idx, j] = f[:, np.searchsorted(idx, j)]
    return out


@pytest.mark.parametrize("strategy", ["halo", "gather"])
def test_columns_and_groups_as_by_the_definition(spark, strategy):
    a = banded(40, 3) + 6 * np.eye(40)
    m, fn = rows(spark, a), MatFn.inverse("lu")
    single = to_dense(submatrix_apply(m, fn, strategy=strategy, parts=5), 40)
    assert np.allclose(single, plain_submatrix(a, fn, [[j] for j in range(40)]) * (a != 0))
    groups = [list(range(i, min(i + 3, 40))) for i in range(0, 40, 3)]
    g = spark.createDataFrame([(c[0], j) for c in groups for j in c], "group_id long, member long")
    merged = to_dense(submatrix_apply(m, fn, g, result_pattern="merged", strategy=strategy), 40)
    assert np.allclose(merged, plain_submatrix(a, fn, groups))
    assert (merged != 0).sum() > (a != 0).sum()
    error = [np.abs(x - np.linalg.inv(a))[a != 0].max() for x in (single, merged)]
    assert error[1] < error[0]


def test_exact_when_it_must_be(spark):
    a = np.kron(np.eye(6), banded(5, 4, 5)) + 9 * np.eye(30)  # blocks
    assert np.allclose(to_dense(submatrix_apply(rows(spark, a), MatFn.inverse("lu")), 30), np.linalg.inv(a))
    b = banded(20, 5) + 8 * np.eye(20)
    whole = submatrix_apply(rows(spark, b), MatFn.inverse("lu"), patterns.one_group(patterns.places(rows(spark, b))), result_pattern="merged")
    assert np.allclose(to_dense(whole, 20), np.linalg.inv(b))
    full = banded(10, 6, 10) + 9 * np.eye(10)
    assert np.allclose(to_dense(submatrix_apply(rows(spark, full), MatFn.sqrt()), 10) @ np.eye(10), MatFn.sqrt()(full))


def test_edge_matrices(spark):
    none = spark.createDataFrame([], matrix.MAT)
    assert submatrix_apply(none, MatFn.inverse()).count() == 0
    one = spark.createDataFrame([(7, 7, 4.0), (9, 9, 2.0)], matrix.MAT)
    assert {r.row: round(r.val, 9) for r in submatrix_apply(one, MatFn.inverse()).collect()} == {7: 0.25, 9: 0.5}
    hub = np.eye(30) * 40
    hub[0], hub[:, 0] = 1, 1
    hub[0, 0] = 40
    p = patterns.places(rows(spark, hub))
    gp = patterns.group_pattern(p, patterns.single_groups(p))
    quantiles, top = patterns.hub_report(gp, 1)
    assert quantiles.first().largest == 30 and top.first().group_id == 0
    with pytest.raises(balance.TooExpensive):
        balance.explain(gp, most_n=20)
    with pytest.raises(balance.TooExpensive):
        balance.explain(gp, budget_flops=10.0)
    assert "30 submatrices" in str(balance.explain(gp))


def test_locality_tells_good_from_bad(spark):
    good = locality_report(rows(spark, banded(60, 7) * 0.1 + 3 * np.eye(60)), MatFn.inverse("lu"), share=1.0)
    bad = locality_report(rows(spark, banded(60, 7) * 0.1 + 0.9 * np.eye(60)), MatFn.inverse("lu"), share=1.0)
    assert good.count() == 60
    assert 20 * good.agg(F.max("leak")).first()[0] < bad.agg(F.max("leak")).first()[0]


def test_parts_have_like_costs(spark):
    gp = spark.range(3000).select(F.col("id").alias("group_id"), (F.pmod(F.xxhash64("id"), F.lit(100)) + 20).alias("n"))
    b = balance.balance(gp, 12).groupBy("part_id").agg(F.sum(F.pow("n", F.lit(3))).alias("c")).toPandas()
    assert len(b) == 12 and b.c.max() < 1.6 * b.c.mean()
    assert balance.balance(gp, 12).count() == 3000


# ---- the pair


def test_pair_against_dense_solution(spark, water):
    a, box, pair, h, s, d, w = water
    n, electrons = len(h), 192 * 8 / 3
    assert np.trace(d @ s) * 2 == pytest.approx(electrons)
    out = cut(paired_purify(pair, Purification(mu=MU), lattice.atom_groups(a)))
    got, on = to_dense(entries_of(out, "d"), n), (h != 0) | (s != 0)
    assert np.abs(got - d)[on].max() < 1e-3 and np.abs(to_dense(entries_of(out, "w"), n) - w)[on].max() < 1e-3
    sums = observables.sums_by(out, pair).first()
    assert observables.energy_error(sums.energy, np.sum(d * h), 192)["relative"] < 1e-5
    assert 2 * sums.electrons == pytest.approx(electrons, rel=1e-4)
    m = metrics_of(out)
    assert m.count() == 192 and m.agg(F.max("resid")).first()[0] < 1e-8
    assert np.abs(got - got.T).max() < 1e-3


def test_generated_halo_and_gather_agree(spark, water):
    a, box, pair, h, s, d, w = water
    how = Purification(mu=MU, solver="eigen")
    g = cut(generate.generate_density(a, box, ElementModel(), how))
    halo = entries_of(paired_purify(pair, how, lattice.atom_groups(a)), "d")
    gather = entries_of(paired_purify(pair, how, lattice.atom_groups(a), strategy="gather", parts=7), "d")
    n = len(h)
    x, y, z = (to_dense(f, n) for f in (entries_of(g, "d"), halo, gather))
    assert np.abs(x - y).max() < 1e-9 and np.abs(y - z).max() < 1e-12
    assert np.abs(to_dense(entries_of(g, "h"), n) - h).max() < 1e-12 and np.abs(to_dense(entries_of(g, "s"), n) - s).max() < 1e-12
    e = generate.energies(g).first()
    assert e.energy == pytest.approx(observables.electronic_energy(cut(halo), pair.select("row", "col", F.col("h").alias("val"))))
    single = generate.generate_density(a, box, ElementModel(), how, element_dtype="float32")
    assert np.abs(to_dense(entries_of(single, "d"), n) - x).max() < 1e-4


def test_merged_groups_in_the_generated_route(spark, water):
    a, box, pair, h, s, d, w = water
    molecules = a.select((F.floor(F.col("atom_id") / 3) * 3).alias("group_id"), F.col("atom_id").alias("member"))
    how = Purification(mu=MU, solver="eigen")
    out = cut(generate.generate_density(a, box, ElementModel(), how, groups=molecules))
    assert metrics_of(out).count() == 64
    atoms_e = generate.energies(generate.generate_density(a, box, ElementModel(), how)).first().energy
    exact = np.sum(d * h)
    assert abs(generate.energies(out).first().energy - exact) <= abs(atoms_e - exact) * 1.5 + 1e-9
    on = (h != 0) | (s != 0)
    assert np.abs(to_dense(entries_of(out, "d"), len(h)) - d)[on].max() < 1e-3


def test_no_shuffle_after_the_dense_stage(spark, water):
    a, box, *_ = water
    plan = generate.generate_density(a, box, ElementModel(), Purification(mu=MU))._jdf.queryExecution().executedPlan().toString()
    above = plan.split("FlatMapGroupsInArrow")[0]
    assert "Exchange" not in above


def test_neighbours_are_those_of_all_pairs(spark, water):
    a, box, *_ = water
    for reach in (2.0, 4.5, 7.5):
        got = lattice.neighbours(a, box, reach).select("i", "j", F.round("r", 9).alias("r"))
        want = lattice.neighbours_nested(a, box, reach).select("i", "j", F.round("r", 9).alias("r"))
        assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_mixed_lattice_has_two_size_classes(spark):
    a, box = workloads.mixed(spark, "/root/testdata/sf0.01")
    p = workloads.atom_places(a, box)
    gp = patterns.weighted_size(patterns.group_pattern(p, patterns.single_groups(p)), a.select(F.col("atom_id").alias("member"), F.col("nbf").alias("weight")))
    n = gp.join(a.select(F.col("atom_id").alias("group_id"), "species"), "group_id")
    far = n.where("species = 'X'").agg(F.min("n")).first()[0]
    assert far > 2 * n.where("species <> 'X'").agg(F.expr("percentile(n, 0.5)")).first()[0]


def test_neutralised_system(spark, water):
    a = water[0]
    b = lattice.neutralise(a, 5)
    assert b.count() == 192 - 10 and b.where("species = 'X'").count() == 5
    last = b.orderBy(F.desc("bf0")).first()
    assert last.bf0 + last.nbf == b.agg(F.sum("nbf")).first()[0]
    assert sorted(map(tuple, b.collect())) == sorted(map(tuple, lattice.neutralise(a.repartition(3), 5).collect()))


# ---- potential


def test_potential_by_levels_and_by_bisection(spark, water):
    a, box, pair, *_ = water
    groups = lattice.atom_groups(a)
    s = potential.find_mu_spectral(pair, groups, 512.0, -2.0, 1.0, tol=0.05)
    assert abs(s["residual"]) <= 0.05 and -0.5 < s["mu"] < -0.05
    r = potential.find_mu_rerun(pair, groups, 512.0, -0.6, 0.0, tol=0.05, rounds=4)
    assert abs(r["residual"]) <= 0.05
    with pytest.raises(potential.NotBracketed):
        potential.find_mu_spectral(pair, groups, 5000.0, -2.0, 1.0)


# ---- baselines


def test_global_schemes_agree_with_dense(spark):
    h, s = banded(24, 8, 1) + np.diag(np.where(np.arange(24) % 2, 4.0, -4.0)), np.eye(24) + 0.05 * banded(24, 9, 1)
    pair_h, pair_s = rows(spark, h), rows(spark, s)
    exact = baselines.dense_density(cut(patterns.pair_rows(pair_h, pair_s)), 0.0)[1]
    assert np.abs(to_dense(baselines.global_density(pair_h, pair_s, 0.0, 4, 9), 24) - exact).max() < 1e-4
    near = to_dense(baselines.orthogonalised_density(pair_h, pair_s, 0.0, k_inverse=5), 24)
    assert np.abs(near - exact).max() < 5e-2
    d = baselines.from_dense(spark, np.arange(24), exact)
    r = observables.residuals(d, pair_s, pair_h)
    assert max(r["idempotency"], r["commutator"], r["asymmetry"]) < 1e-9 and r["trace"] == pytest.approx(12)


# ---- merging


def plain_greedy(lists):
    """All accepted merges one by one, by (added, -gain, ids), recomputed each time."""
    lists, own = {g: set(v) for g, v in lists.items()}, {g: {g} for g in lists}
    while True:
        best = None
        for i in lists:
            for j in lists:
                if i < j and (lists[i] & own[j] or lists[j] & own[i]):
                    a, b, u = len(lists[i]), len(lists[j]), len(lists[i] | lists[j])
                    if u**3 < a**3 + b**3:
                        c = (u - max(a, b), u**3 - a**3 - b**3, i, j)
                        best = min(best, c) if best else c
        if best is None:
            return {g: sorted(m) for g, m in own.items()}
        _, _, i, j = best
        lists[i] |= lists.pop(j)
        own[i] |= own.pop(j)


def test_greedy_is_the_plain_greedy():
    draw = np.random.default_rng(4)
    for _ in range(6):
        at = draw.random((40, 2)) * 4
        near = ((at[:, None] - at[None]) ** 2).sum(2) < 1.0
        lists = {i: set(np.flatnonzero(near[i]).tolist()) for i in range(40)}
        got = combine.greedy(lists, {i: [i] for i in range(40)})
        assert {g: sorted(m) for g, m in got.items()} == plain_greedy(lists)


def check_merge(before, after, weight=None):
    own = [m for r in after for m in r.own]
    assert sorted(own) == sorted(m for r in before for m in r.own)
    lists = {m: set(r.idx) for r in before for m in r.own}
    for r in after:
        assert set(r.idx) == set().union(*(lists[m] for m in r.own)) and r.group_id == min(r.own)
        assert r.n == sum(weight[m] if weight else 1 for m in r.idx)
    before_n3 = sum(sum(weight[m] if weight else 1 for m in r.idx) ** 3 for r in before)
    assert sum(r.n**3 for r in after) <= before_n3


def test_merging_lowers_the_work(spark, water):
    a, box, *_ = water
    p = workloads.atom_places(a, box, reach=3.5)
    gp = cut(patterns.group_pattern(p, patterns.single_groups(p)))
    cells = a.select(F.col("atom_id").alias("group_id"), F.col("cell_id").alias("cell"))
    for border in ("ignore", "second_pass"):
        by_cell = cut(combine.combine_subcells(gp, cells, border=border))
        check_merge(gp.collect(), by_cell.collect())
        r = observables.reduction(gp, by_cell)
        assert r["cubic"] > 1.2 and r["quadratic"] > r["cubic"] and r["count"] > 2
    weights = a.select(F.col("atom_id").alias("member"), F.col("nbf").alias("weight"))
    check_merge(gp.collect(), combine.combine_subcells(gp, cells, weights).collect(), {r.member: r.weight for r in weights.collect()})
    k = combine.combine_kmeans(a, 20, 3)
    assert k.count() == 192 and k.select("group_id").distinct().count() <= 20


def test_rounds_end_where_no_merge_pays(spark):
    draw = np.random.default_rng(4)
    at = draw.random((60, 2)) * 5
    near = ((at[:, None] - at[None]) ** 2).sum(2) < 1.0
    p = cut(spark.createDataFrame([(int(i), int(j)) for i, j in np.argwhere(near)], "row long, col long"))
    gp = cut(patterns.group_pattern(p, patterns.single_groups(p)))
    weight = {m: 1 + m % 4 for m in range(60)}
    weights = spark.createDataFrame(sorted(weight.items()), "member long, weight long")
    for w, own in ((None, None), (weights, weight)):
        after, rounds = combine.combine(gp, w)
        check_merge(gp.collect(), after.collect(), own)
        assert sum(n for _, n in rounds) == 60 - after.count() > 10
        assert combine.merge_candidates(after, w).where("gain > 0").count() == 0
    other, _ = combine.combine(gp.repartition(7, "n"), weights)
    assert sorted(r.own for r in other.collect()) == sorted(r.own for r in after.collect())
    with pytest.raises(RuntimeError):
        combine.combine(gp, most_rounds=1)


def test_a_centre_is_the_nearest_of_all(spark):
    draw = np.random.default_rng(6)
    at, centres = draw.random((200, 3)) * 10, draw.random((15, 3)) * [10, 10, 2]
    a = spark.createDataFrame([(i, *map(float, x)) for i, x in enumerate(at)], "atom_id long, x double, y double, z double")
    c = spark.createDataFrame([(i, *map(float, x)) for i, x in enumerate(centres)], "c long, cx double, cy double, cz double")
    want = ((at[:, None] - centres[None]) ** 2).sum(2).argmin(1)
    for width in (0.7, 40.0):
        assert {r.atom_id: r.c for r in combine.nearest_centre(a, c, width).collect()} == dict(enumerate(want.tolist()))


def test_a_merge_is_kept_while_it_covers(spark, water):
    a, box, *_ = water
    p = cut(workloads.atom_places(a, box, reach=3.5))
    cells = a.select(F.col("atom_id").alias("group_id"), F.col("cell_id").alias("cell"))
    gp = cut(combine.combine_subcells(patterns.group_pattern(p, patterns.single_groups(p)), cells))
    assert combine.still_valid(gp, p).where("not covers").count() == 0
    moved = cut(p.union(spark.createDataFrame([(0, 100), (100, 0)], "row long, col long")).distinct())
    stale = combine.still_valid(gp, moved).where("not covers").count()
    assert 1 <= stale <= 2
    new = combine.refresh(gp, moved)
    assert combine.still_valid(new, moved).where("not covers").count() == 0
    assert sorted(m for r in new.collect() for m in r.own) == list(range(192))


def test_equal_lists_are_joined_in_one_round(spark):
    lists = [(g, [x for x in range(40) if x % 4 == g % 4], [g]) for g in range(40)] + [(50, [0, 4, 60], [50]), (51, [0, 4, 60], [51])]
    gp = cut(spark.createDataFrame(lists, "group_id long, idx array<long>, own array<long>"))
    after, rounds = combine.combine(gp)
    got = {r.group_id: (r.idx, r.own, r.n) for r in after.collect()}
    assert rounds == [(0, 36)] and got == {g: ([*range(g, 40, 4)],) * 2 + (10,) for g in range(4)} | {g: ([0, 4, 60], [g], 3) for g in (50, 51)}
    pieces = combine.combine_subcells(gp.where("group_id < 40"), F.floor(F.col("group_id") / 20), border="ignore").collect()
    assert sorted((r.group_id, len(r.own), r.n) for r in pieces) == [(g, 5, 10) for g in (0, 1, 2, 3, 20, 21, 22, 23)]


def test_equal_lists_are_exploded_once(spark, monkeypatch):
    """Sizes are added up for each different list, not for each group, and no list is broadcast."""
    lists = spark.createDataFrame([(g, list(range(g % 4, 400, 4)), [g]) for g in range(400)], "group_id long, idx array<long>, own array<long>")
    weights = spark.createDataFrame([(m, 1 + m % 3) for m in range(400)], "member long, weight long")
    seen, sizes = [], combine.with_sizes

    def counted(gp, w):
        seen.append(gp.count())
        out = sizes(gp, w)
        assert "strategy=merge" in out._jdf.queryExecution().analyzed().toString()
        return out

    monkeypatch.setattr(combine, "with_sizes", counted)
    after, rounds = combine.combine(lists, weights)
    assert rounds == [(0, 396)] and seen == [4]
    assert {r.group_id: (len(r.own), r.n) for r in after.collect()} == {g: (100, sum(1 + m % 3 for m in range(g, 400, 4))) for g in range(4)}


def test_pairs_that_pay_are_all_among_those_counted(spark):
    """Groups of several members, members without an owner or with two, and ids of many blocks."""
    draw = np.random.default_rng(7)
    rows = []
    for g in range(90):
        near = {(g + int(d)) % 90 for d in draw.integers(-6, 7, 9)} | {g}
        rows.append((g * 9000, sorted(x * 9000 for x in near) + [10**9 + g // 3], [g * 9000]))
    rows += [(10**7, [0, 9000, 18000], [0, 10**7]), (10**7 + 1, list(range(1, 700)), [10**7 + 1]), (10**7 + 2, list(range(1, 690)) + [10**7 + 1], [10**7 + 2]), (10**7 + 3, [4], [])]
    gp = cut(spark.createDataFrame(rows, "group_id long, idx array<long>, own array<long>"))
    key = lambda df: sorted(tuple(r) for r in df.collect())
    want = key(combine.merge_candidates(gp).where("gain > 0"))
    assert key(combine.paying(gp)) == want and len(want) > 10
    apart = gp.where("group_id >= 10000001 and group_id <> 10000002")
    assert key(combine.paying(apart)) == key(combine.merge_candidates(apart).where("gain > 0")) == []


def test_no_pair_of_a_random_like_graph_is_counted_out(spark, monkeypatch):
    """Parts bought together: lists come from orders, and nearly all pairs are left out by their marks."""
    from nearfield.queries import QUERIES

    middle = "/root/testdata/sf0.01"
    gp = cut(workloads.copart_lists(spark, middle))
    p = patterns.places(workloads.copart(spark, middle))
    key = lambda df: sorted(tuple(r) for r in df.select("group_id", "idx", "own").collect())
    assert key(gp) == key(patterns.group_pattern(p, patterns.single_groups(p)))
    pairs = gp.selectExpr("sum(size(idx) - 1) / 2").first()[0]
    assert combine.may_pay(gp).count() < pairs / 100
    monkeypatch.setattr(workloads, "copart", None)
    monkeypatch.setattr(combine, "merge_candidates", None)
    assert QUERIES["combine_copart_none"](spark, middle).first().groups == gp.count()


def test_a_dense_reference_needs_room_for_a_component_only(spark):
    a = np.kron(np.eye(4), banded(5, 3) + 9 * np.eye(5))
    order = np.random.default_rng(1).permutation(20)
    a = a[np.ix_(order, order)]
    got = baselines.dense_reference(rows(spark, a), MatFn.inverse("cholesky"), max_dim=5)
    assert np.allclose(to_dense(got, 20), np.linalg.inv(a)) and got.count() == 100
    with pytest.raises(matrix.MatrixError):
        baselines.dense_reference(rows(spark, a), MatFn.inverse("cholesky"), max_dim=4)


def test_components_make_a_group_each(spark):
    path = [(3 * i % 31, 3 * (i + 1) % 31) for i in range(20)]
    star = [(100 + i, 99 + 100) for i in range(30)] + [(500, 500)]
    got = {r.member: r.group_id for r in patterns.component_groups(spark.createDataFrame(path + star, "row long, col long")).collect()}
    assert got == {x: 0 for e in path for x in e} | {x: 100 for e in star for x in e if x != 500} | {500: 500}


def test_members_of_sets_are_counted_by_tiles(spark, monkeypatch):
    """Pairs of a set over several batches, repeated and null members, ids below zero and of far tiles; no pair is a row of a shuffle."""
    for name, v in (("MET", 8), ("MET_ROWS", 50), ("MET_PAIRS", 90)):
        monkeypatch.setattr(workloads, name, v)
    draw = np.random.default_rng(8)
    sets = [(int(k), int(m)) for k, m in zip(draw.integers(0, 60, 400), draw.integers(-9, 30, 400), strict=True)] + [(99, 3 * m) for m in range(70)] + [(5, 10**12), (6, 10**12)]
    got = workloads.met_in_sets(spark.createDataFrame([*sets, (None, 1), (1, None)], "key long, member long"))
    assert "Join" not in got._jdf.queryExecution().optimizedPlan().toString()
    want = {}
    for k in {k for k, _ in sets}:
        held = {m for j, m in sets if j == k}
        for x in held:
            for y in held - {x}:
                want[x, y] = want.get((x, y), 0) + 1
    rows_got = got.collect()
    assert {(r.row, r.col): r.val for r in rows_got} == want and len(rows_got) == len(want)


def test_entries_go_to_groups_as_parts_of_columns(spark, monkeypatch):
    """Rows without a column, columns without a diagonal, stored zeros and small entries; entries meet no join as rows."""
    from nearfield.operators import submatrix

    entries = [(0, 1, 2.0), (1, 0, 2.0), (1, 1, 3.0), (2, 1, 0.5), (3, 4, 0.0), (4, 3, 1e-3), (5, 5, 0.0), (7, 6, 4.0)]
    m = spark.createDataFrame(entries, "row long, col long, val double").repartition(3)
    dense = np.zeros((8, 8))
    for i, j, v in entries:
        dense[i, j] = v
    monkeypatch.setattr(submatrix, "places", None)
    for tol in (0.0, 0.1):
        kept = np.where((np.abs(dense) > tol) | np.eye(8, dtype=bool), dense, 0.0)
        stored = (np.abs(dense) > tol) | np.eye(8, dtype=bool)
        for strategy in ("halo", "gather"):
            groups = spark.createDataFrame([(0, i) for i in range(8)], "group_id long, member long")
            out = submatrix.submatrix_apply(m, MatFn.poly((0.0, 0.0, 1.0)), groups, drop_tol=tol, result_pattern="merged", strategy=strategy)
            assert out.columns == ["row", "col", "val"] and np.allclose(to_dense(out, 8), kept @ kept) and out.count() == 64
            own = submatrix.submatrix_apply(m, MatFn.poly((0.0, 1.0)), drop_tol=tol, strategy=strategy).collect()
            assert {(r.row, r.col): r.val for r in own} == {(int(i), int(j)): kept[i, j] for i, j in np.argwhere(stored)}
    assert submatrix.column_parts(m.coalesce(1), ["val"]).count() == 8


def test_a_task_joins_what_its_places_connect(spark, monkeypatch):
    monkeypatch.setattr(patterns, "JOINED", 40)
    draw = np.random.default_rng(9)
    places = [(i, j) for b in range(4) for i, j in draw.integers(50 * b, 50 * b + 50, (300, 2)).tolist()] + [(500, 500)]
    e = spark.createDataFrame(places, "a long, b long").repartition(2)
    assert patterns.contracted(e).count() <= 2 * 201
    got = {r.node: r.component for r in patterns.components(e.toDF("row", "col")).collect()}
    least = {}
    for b in range(5):
        nodes = sorted({x for p in places for x in p if (x // 50 == b if b < 4 else x == 500)})
        least |= dict.fromkeys(nodes, nodes[0])
    assert got == least


def test_blocks_are_made_and_multiplied_in_parts(spark, monkeypatch):
    """Entries of a block in several tasks, ids of far blocks and below zero; a task sends a row for each block or tile that it meets."""
    monkeypatch.setattr(matrix, "PACKED", 20)
    monkeypatch.setattr(matrix, "FILLED", 3)
    monkeypatch.setattr(matrix, "TILE", 8)
    a = banded(22, 4, 6)
    entries = [(int(i) * 3 - 10, int(j) * 3 - 10, float(a[i, j])) for i, j in np.argwhere(a)]
    m = spark.createDataFrame(entries, "row long, col long, val double").repartition(5)
    b = matrix.blocks_of(m, 4)
    assert "map_from_entries" not in b._jdf.queryExecution().analyzed().toString()
    assert {(r.bi * 4 + k // 4, r.bj * 4 + k % 4): v for r in b.collect() for k, v in enumerate(r.v) if v} == {(i, j): v for i, j, v in entries}
    got = matrix.multiply_blocks(cut(b), cut(b), 4)
    assert "data#" in got._jdf.queryExecution().analyzed().toString()
    square = a @ a
    want = {(int(i) * 3 - 10, int(j) * 3 - 10): square[i, j] for i, j in np.argwhere(square)}
    found = {(r.row, r.col): r.val for r in got.collect()}
    assert found.keys() >= {k for k, v in want.items() if abs(v) > 1e-9} and all(abs(found.get(k, 0) - want.get(k, 0)) < 1e-9 for k in found.keys() | want.keys())


def test_a_product_of_blocks_over_several_tiles(spark, monkeypatch):
    monkeypatch.setattr(matrix, "TILE", 8)
    a, b = banded(30, 1, 9), banded(30, 2, 3)
    x, y = cut(matrix.blocks_of(rows(spark, a), 4)), cut(matrix.blocks_of(rows(spark, b), 4))
    got = matrix.multiply_blocks(x, y, 4)
    assert "lambdafunction" not in got._jdf.queryExecution().optimizedPlan().toString()  # no cell by cell sums in SQL
    assert np.allclose(to_dense(got, 30), a @ b) and got.count() == got.select("row", "col").distinct().count()


def test_nothing_merges_in_a_random_graph(spark):
    p = patterns.places(workloads.copart(spark, SMALL))
    gp = cut(patterns.group_pattern(p, patterns.single_groups(p)))
    assert combine.merge_candidates(gp).where("gain > 0").count() == 0


# ---- measures


def test_measures(spark):
    runs = spark.createDataFrame([("a", 1, 8.0), ("a", 2, 4.0), ("a", 4, 4.0)], "series string, workers int, seconds double")
    assert [r.efficiency for r in observables.efficiency(runs).orderBy("workers").collect()] == [1.0, 1.0, 0.5]
    assert [r.efficiency for r in observables.efficiency(runs, "weak").orderBy("workers").collect()] == [1.0, 2.0, 2.0]
    t = observables.StageTimer()
    for _ in range(3):
        assert t.time("x", lambda: 5) == 5
    assert t.mean("x", 3) >= 0 and observables.sustained(10, 2) == 5 and observables.peak_fraction(5, 10) == 0.5
    with pytest.raises(ValueError):
        t.mean("x", 4)
    gp = spark.createDataFrame([(1, 10_000)] * 3, "group_id long, n long")
    assert observables.flops(gp, 8, 20).first().all_flops == 3 * 2 * 69 * 10**12
    pivot = observables.histogram_pivot(gp, gp.limit(1)).first()
    assert (pivot.before, pivot.after) == (3, 1)
    assert observables.measured_peak(128, 1) > 0 and observables.total_energy(-1.0, ions=0.5)["total"] == -0.5


# ---- dynamics


def test_forces_are_the_energy_s_derivative(spark, water):
    a, box, *_ = water
    model, how = ElementModel(), Purification(mu=MU, solver="eigen")
    whole = a.select(F.lit(0).cast("long").alias("group_id"), F.col("atom_id").alias("member"))

    def energy(move):
        moved = cut(a.withColumn("x", F.col("x") + F.when(F.col("atom_id") == 7, move).otherwise(0.0)))
        pair = cut(lattice.matrix_from_atoms(moved, box, model))
        ids, d, w = baselines.dense_density(pair, MU)
        _, h = baselines.dense(pair, value="h")
        return float(np.sum(d * h)), pair, d, w

    e1, e2 = energy(1e-4)[0], energy(-1e-4)[0]
    _, pair, d, w = energy(0.0)
    n = np.arange(len(d))
    both = baselines.from_dense(spark, n, d).withColumnRenamed("val", "d").join(baselines.from_dense(spark, n, w).withColumnRenamed("val", "w"), ["row", "col"])
    f = {r.atom_id: r for r in dynamics.forces(both, a, box, model).collect()}
    assert f[7].fx == pytest.approx(-(e1 - e2) / 2e-4, abs=1e-6)
    assert abs(sum(r.fx for r in f.values())) < 1e-9 and len(f) == 192
    out = generate.generate_density(a, box, model, how)
    near = {r.atom_id: r.fx for r in dynamics.forces(cut(out), a, box, model).collect()}
    assert max(abs(near[i] - f[i].fx) for i in f) < 1e-3


def oscillators(spark, n=50):
    s = spark.range(n).select(F.col("id").alias("atom_id"), F.lit(1.0).alias("mass"), *[F.lit(1.0).alias(c) for c in "xyz"], *[F.lit(0.0).alias(f"v{c}") for c in "xyz"])
    return s.withColumns({f"f{c}": -F.col(c) for c in "xyz"})


def spring(m):
    return m.select("atom_id", *[(-F.col(c)).alias(f"f{c}") for c in "xyz"])


@pytest.mark.parametrize("scheme", ["splitting", "second_order"])
def test_energy_is_kept_without_noise_and_lost_to_friction(spark, scheme):
    for gamma, low, high in ((0.0, 2.98, 3.02), (0.3, 0.1, 2.9)):
        s = oscillators(spark, 1)
        for k in range(12):
            s = dynamics.langevin_step(s, spring, gamma, 0.1, scheme)
            s = cut(s) if k % 4 == 3 else s
        r = s.first()
        e = r.vx**2 + r.vy**2 + r.vz**2 + r.x**2 + r.y**2 + r.z**2
        assert low < e < high
    with pytest.raises(ValueError):
        dynamics.langevin_step(s, spring, 0.1, 0.1, "other")


def test_white_noise_gives_back_its_friction(spark):
    draw = np.random.default_rng(5)
    white = draw.normal(0, 2.0, (20, 500))
    make = lambda x: spark.createDataFrame([(i, t, float(v)) for i, r in enumerate(x) for t, v in enumerate(r)], "id int, t int, v double")
    report = cut(dynamics.noise_report(make(white), 3))
    assert dynamics.is_white(report)
    # lag covariances above 0 only add noise for white input
    g = dynamics.gamma_from_noise(report.where("lag = 0"), 1.5, 2.0, 0.5).first().gamma
    assert g == pytest.approx(4.0 * 0.5 / (2 * 1.5 * 2.0), rel=0.05)
    coloured = white[:, 1:] + 0.5 * white[:, :-1]
    assert not dynamics.is_white(dynamics.noise_report(make(coloured), 3))


def test_calibration_finds_the_temperature(spark):
    noise = lambda k, n: (F.pmod(F.xxhash64("atom_id", F.lit(k), F.lit(n)), F.lit(20001)) / 10000.0 - 1) * 4
    force = lambda m, n: m.select("atom_id", *[(-F.col(c) + noise(i, n)).alias(f"f{c}") for i, c in enumerate("xyz")])
    s = oscillators(spark, 400)
    gamma, trace = dynamics.calibrate_gamma(s, force, target=1.0, dt=0.2, steps=14, tau=0.5, gamma=0.1)
    assert len(trace) == 14 and trace[-1][1] > trace[0][1] and gamma >= 0
    assert dynamics.next_gamma(0.0, 0.5, 1.0, 0.1, 1.0, 1.0) == 0.0


def test_steps_of_electronic_structure_dynamics(spark, water):
    a, box, *_ = water
    cfg = dynamics.StepConfig(box, ElementModel(), Purification(mu=MU, solver="eigen"), dt=0.5)
    s = dynamics.start_state(a, cfg, speed=0.02)
    after, seen = dynamics.simulate(s, cfg, 2)  # two whole steps
    total = [o["energy"] + o["kinetic"] for o in seen]
    assert abs(total[1] - total[0]) < 2e-3 * abs(total[0]) and after.count() == 192
    assert 2 * seen[0]["electrons"] == pytest.approx(512, rel=1e-3)


def test_force_noise_of_half_precision(spark, water):
    a, box, *_ = water
    f = {}
    for operand in ("fp64", "half"):
        out = cut(generate.generate_density(a, box, ElementModel(), Purification(mu=MU, operand=operand, k_inverse=8, k_sign=12)))
        f[operand] = dynamics.forces(out, a, box, ElementModel()).withColumn("step", F.lit(0))
    noise = dynamics.force_noise(f["half"], f["fp64"]).agg(F.stddev("nx").alias("sd"), F.avg("nx").alias("mean")).first()
    assert 0 < noise.sd < 0.05 and abs(noise.mean) < noise.sd


def test_ewald_sum_of_rock_salt(spark):
    box = lattice.Box(1, 1, 1)
    e = box.edges[0]
    ions = [(i * 4 + j * 2 + k, i * e / 2, j * e / 2, k * e / 2, float((-1) ** (i + j + k))) for i in range(2) for j in range(2) for k in range(2)]
    q = spark.createDataFrame(ions, "atom_id long, x double, y double, z double, q double")
    assert dynamics.ewald_energy(q, box) / 4 * (e / 2) == pytest.approx(-1.747565, abs=2e-4)
    assert dynamics.ewald_energy(q, box, alpha=0.8, kmax=8) == pytest.approx(dynamics.ewald_energy(q, box), abs=1e-4)
    assert dynamics.dispersion(q.withColumn("species", F.lit("X")), box, 9.0) < 0


def test_self_consistency_and_propagation(spark):
    h0, s = np.diag([-1.0, 1.0, -0.8, 1.2]) + 0.1 * banded(4, 1), np.eye(4)

    def h_of(d):
        base = rows(spark, h0)
        if d is None:
            return base
        return matrix.axpy(1.0, base, 0.2, d.where("row = col"))

    def density(h):
        pair = patterns.pair_rows(h, rows(spark, s))
        return entries_of(paired_purify(cut(pair), Purification(solver="eigen"), patterns.one_group(patterns.places(h)), result_pattern="merged"), "d")

    d, changes = dynamics.scf(h_of, density, mixing=0.7, tol=1e-3, most=4)
    assert changes[-1] < changes[0] / 5 and matrix.trace(d) == pytest.approx(2.0, abs=1e-2)
    same = dynamics.propagate([d, d, d])
    assert matrix.difference(same, d).first().max_abs < 1e-9
    line = [matrix.scale(d, 1 + 0.1 * t) for t in range(3)]
    assert matrix.difference(dynamics.propagate(line[1:]), matrix.scale(d, 1.3)).first().max_abs < 1e-9


def test_averages_have_errors(spark):
    t = spark.range(1000).select(F.col("id").alias("step"), (F.col("id") % 2).cast("double").alias("v"))
    r = dynamics.ensemble_average(t, "v").first()
    assert r["mean"] == 0.5 and r["error"] == 0 and r["blocks"] == 10


def test_the_duplicate_graph_holds_large_families(spark, tmp_path):
    from nearfield.queries import QUERIES

    texts = {d: f"a b c d e f {'g' if d % 2 else 'h'}" for d in range(70)} | {100: "a b c d e", 101: "k l m n o p", 102: "k l m n o q", 103: "alone with these own few words", 104: None}
    y = {d: d % 3 % 2 for d in texts if d % 4 < 2 and d != 102}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(list(y.items()) + [(2, None)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    sets = {d: {tuple(t.split()[i : i + 5]) for i in range(max(1, len(t.split()) - 4))} for d, t in texts.items() if t}
    a = {d: {e: n for e in sets if e != d and (n := len(sets[d] & sets[e]))} for d in sets}
    times = lambda v: {d: sum(n * v[e] for e, n in near.items() if e in v) for d, near in a.items() if any(e in v for e in near)}
    one = times(y)
    two = times(one)
    want = {d: two.get(d, 0) + 2 * one.get(d, 0) for d in two | one}
    got = QUERIES["dup_graph_filter"](spark, str(tmp_path)).collect()
    assert len(got) == len(want) and {r.doc_id: r.filtered for r in got} == want and set(range(70)) <= set(want)
