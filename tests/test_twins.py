"""Reduced matrices of like rows against the full ones, and the queries on cliques at their work."""

import duckdb
import numpy as np
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from nearfield import experiments, queries  # noqa: F401  (registers more queries)
from nearfield.functions import kernels as k
from nearfield.operators import patterns, twins, workloads
from nearfield.queries import ORACLES, QUERIES


def full_and_reduced(counts, on, between):
    """A matrix of classes (entries ``between`` them, diagonals with ``on`` more), its reduced form, and both bases' map."""
    of = np.repeat(np.arange(len(counts)), counts)
    full = between[of[:, None], of[None, :]] + np.diag(on[of])
    n = np.asarray(counts, float)
    small = np.zeros((2 * len(n), 2 * len(n)))
    small[0::2, 0::2] = between * np.sqrt(n[:, None] * n[None, :]) + np.diag(on)
    small[range(1, len(small), 2), range(1, len(small), 2)] = on
    return full, small, of


def grown(small, space, of):
    off, more = space.entries(small)
    return off[of[:, None], of[None, :]] + np.diag(more[of])


COUNTS = [1, 4, 7]
ON = np.array([3.0, -2.0, 2.5])
BETWEEN = np.array([[0.3, 0.1, -0.05], [0.1, -0.2, 0.04], [-0.05, 0.04, 0.1]])


def test_norms_are_those_of_the_full_matrix():
    full, small, of = full_and_reduced(COUNTS, ON, BETWEEN)
    space = k.Twins(COUNTS)
    assert np.allclose(grown(small, space, of), full, atol=1e-14)
    assert space.size(small) == len(full)
    assert np.isclose(space.norm(small), np.linalg.norm(full))
    assert np.isclose(space.rows(small), np.abs(full).sum(axis=1).max())
    assert np.isclose(k.scale_of(small, space=space), k.scale_of(full))


@pytest.mark.parametrize("fn", [k.MatFn.sign(), k.MatFn.sign(stop=k.StopRule.fixed(3)), k.MatFn.sign(order=5), k.MatFn.sign(order=2, solver="pade"), k.MatFn.sign(solver="exact"), k.MatFn.spectral(np.exp), k.MatFn.poly((1.0, 2.0, 0.5))])
def test_functions_of_several_classes(fn):
    full, small, of = full_and_reduced(COUNTS, ON, BETWEEN)
    space = k.Twins(COUNTS)
    assert np.allclose(grown(fn(small, space), space, of), fn(full), atol=1e-9)


@pytest.mark.parametrize("fn", [k.MatFn.inverse(), k.MatFn.inverse("lu"), k.MatFn.sqrt(), k.MatFn.inv_sqrt(), k.MatFn.root(3)])
def test_functions_of_positive_matrices(fn):
    full, small, of = full_and_reduced(COUNTS, np.abs(ON), np.abs(BETWEEN) * 0.2)
    space = k.Twins(COUNTS)
    assert np.allclose(grown(fn(small, space), space, of), fn(full), atol=1e-9)


@pytest.mark.parametrize("how", [k.Purification(), k.Purification(k_inverse=3, k_sign=2, pad=16), k.Purification(k_inverse=3, k_sign=2, pad=6), k.Purification(solver="eigen"), k.Purification(inverse="cholesky", solver="pade", k_sign=2)])
def test_purification_takes_the_steps_of_the_full_pair(how):
    h, small_h, of = full_and_reduced(COUNTS, ON, BETWEEN)
    s, small_s, _ = full_and_reduced(COUNTS, np.ones(3), np.abs(BETWEEN) * 0.2)
    space = k.Twins(COUNTS)
    d, w, done = k.purify(h, s, how)
    small_d, small_w, small_done = k.purify(small_h, small_s, how, space=space)
    assert np.allclose(grown(small_d, space, of), d, atol=1e-9) and np.allclose(grown(small_w, space, of), w, atol=1e-9)
    assert (done["k_inverse"], done["k_sign"], done["gemms"]) == (small_done["k_inverse"], small_done["k_sign"], small_done["gemms"])
    assert np.isclose(done["residual"], small_done["residual"], atol=1e-9)


def test_a_stack_is_padded_each_by_its_own_count():
    how, pair = k.Purification(k_inverse=4, k_sign=3, pad=8), []
    for counts in ([8], [5], [1]):
        h, small_h, of = full_and_reduced(counts, np.array([-0.4]), np.array([[0.9 / counts[0]]]))
        s, small_s, _ = full_and_reduced(counts, np.array([1.0]), np.array([[0.5 / counts[0]]]))
        pair.append((counts, of, small_h, small_s, k.purify(h, s, how)[0]))
    space = k.Twins([p[0] for p in pair])
    d = k.purify(np.stack([p[2] for p in pair]), np.stack([p[3] for p in pair]), how, space=space)[0]
    for small, (counts, of, _, _, want) in zip(d, pair, strict=True):
        assert np.allclose(grown(small, k.Twins(counts), of), want, atol=1e-10)


#: Customers of one nation and segment, which at many copies of a table are thousands.
ODD = [(1, 7, "A"), (2, 7, "A"), (3, 7, "A"), (4, 7, "B"), (5, 8, "A"), (6, 8, "A"), (7, None, "A"), (8, None, "A"), (9, 8, None)]


@pytest.fixture(scope="module")
def large_cliques(spark, tmp_path_factory):
    """Two cliques of 1500 rows (over a piece of rows), one of one row, and rows without nation or segment."""
    d = str(tmp_path_factory.mktemp("cliques"))
    rows = spark.createDataFrame(ODD, "c_custkey long, c_nationkey int, c_mktsegment string")
    many = spark.range(10, 3010).select(F.col("id").alias("c_custkey"), (F.col("id") % 2).cast("int").alias("c_nationkey"), F.lit("C").alias("c_mktsegment"))
    rows.unionByName(many).write.parquet(f"{d}/customer.parquet")
    con = duckdb.connect()
    con.sql(f"CREATE VIEW customer AS SELECT * FROM '{d}/customer.parquet/*.parquet'")
    return d, con


ENTRIES = ["exponential_blk", "sign_eigen_blk", "sign_order5_blk", "sign_pade_blk", "sign_four_steps_blk", "paired_density_blk", "energy_weighted_blk", "padded_density_blk", "propagated_density_blk", "stored_matrix_blk"]


@pytest.mark.parametrize("name", ENTRIES)
def test_entries_of_large_cliques(spark, large_cliques, name):
    d, con = large_cliques
    got = QUERIES[name](spark, d).toArrow()  # noqa: F841  (read by name)
    con.sql(f"CREATE OR REPLACE TEMP TABLE want AS {ORACLES[name]}")
    n, m, met = con.sql('SELECT (SELECT count(*) FROM got), (SELECT count(*) FROM want), (SELECT count(*) FROM got g JOIN want w ON g."row" = w."row" AND g.col = w.col AND g.val = w.val)').fetchall()[0]
    assert n == m == met and n > 4_000_000


@pytest.mark.parametrize("name", ["energy_blk", "metrics_blk", "chemical_potential_blk", "involution_residual_blk"])
def test_sums_of_large_cliques(spark, large_cliques, name, monkeypatch):
    """No entries of pairs of rows are made on the way."""
    monkeypatch.setattr(workloads, "cliques", None)
    d, con = large_cliques
    con.sql("CREATE OR REPLACE TEMP VIEW c_ok AS SELECT * FROM customer WHERE c_nationkey IS NOT NULL AND c_mktsegment IS NOT NULL")
    got = QUERIES[name](spark, d)
    want = con.sql(ORACLES[name].replace("FROM customer", "FROM c_ok"))
    at = [want.columns.index(c) for c in got.columns]
    assert sorted(tuple(r) for r in got.collect()) == sorted(tuple(r[i] for i in at) for r in want.fetchall())


def test_reduced_route_gives_what_the_full_one_gives(spark):
    """The same function by the entries of all pairs, which the general route still takes."""
    sf = "/root/testdata/sf0.001"
    full = queries.submatrix_apply(workloads.clique_matrix(spark, sf, 1.0, 0.5), k.MatFn.inverse(), workloads.clique_groups(spark, sf))
    members = workloads.clique_members(spark, sf)
    cliques = members.select("clique", "m").distinct()
    out = twins.expand(queries.submatrix_apply(twins.reduced(cliques, val=workloads.on_off(1.0, 0.5)), k.MatFn.inverse(), twins.reduced_groups(cliques)), members)
    both = full.join(out.withColumnRenamed("val", "v2"), ["row", "col"], "full").agg(F.count("val"), F.count("v2"), F.count(F.lit(1)), F.max(F.abs(F.col("val") - F.col("v2")))).first()
    assert both[0] == both[1] == both[2] > 0 and both[3] < 1e-10
    assert patterns.places(full).count() == both[0]


@pytest.mark.parametrize("name", ["sign_eigen_blk", "sign_order5_blk", "sign_pade_blk"])
def test_entries_are_written_without_levels_of_nulls(spark, tmp_path, name):
    QUERIES[name](spark, "/root/testdata/sf0.001").write.parquet(f"{tmp_path}/out")
    files = list((tmp_path / "out").glob("*.parquet"))
    assert files and all(not f.nullable for x in files for f in pq.read_schema(x))


def test_null_members_stay(spark):
    """Rows of a null member are neither dropped nor given another key."""
    members = spark.createDataFrame([(1, 1, 3), (2, 1, 3), (None, 1, 3)], "member long, clique long, m long")
    m = spark.createDataFrame([(2, 2, 1.0), (3, 3, -1.0)], "row long, col long, val double")
    out = twins.expand(m, members)
    assert sorted((r.row or 0, r.col) for r in out.collect()) == [(0, 1), (0, 2), (1, 1), (1, 2), (2, 1), (2, 2)]
    assert [f.nullable for f in out.schema] == [True, False, False]
