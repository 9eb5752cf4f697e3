"""Queries give the whole result: every sample, window, pair and page part, against brute force."""

import datetime as dt

import numpy as np

from dagframe import workloads
from dagframe.operators import learner
from dagframe.operators import workload_learning as learning


def test_every_customer_is_explained_and_weighed(spark, sf):
    ratings, links = learning._ratings(spark, sf).toPandas(), learning._links(spark, sf).toPandas()
    parts = ratings.merge(links, left_on="node_id", right_on="src").assign(part=lambda f: f["x"] * f["w"], size=lambda f: f["part"].abs())
    parts = parts.sort_values(["size", "src"], ascending=[False, True]).groupby(["sample_id", "dst"]).head(2)
    want = {(s, n, v): p for s, n, v, p in zip(parts["sample_id"], parts["dst"], parts["src"], parts["part"], strict=True)}
    got = {(r["sample_id"], r["node_id"], r["via"]): r["part"] for r in workloads.queries()["explain_scores"](spark, sf).collect()}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-3 for k in got)
    assert {k[0] for k in got} == set(ratings["sample_id"])

    density = {r["sample_id"]: r["log_density"] for r in workloads.queries()["log_density"](spark, sf).collect()}
    x = ratings.pivot(index="sample_id", columns="node_id", values="x").fillna(0.0)
    total = np.zeros(len(x))
    pairs = links[(links["src"] <= 12) & links["dst"].between(13, 15)]
    for child, group in pairs.groupby("dst"):
        a, y = x[sorted(group["src"])].to_numpy(), x[child].to_numpy()
        r = y - a @ np.linalg.lstsq(a, y, rcond=None)[0]
        total += -0.5 * (np.log(2 * np.pi * np.mean(r * r)) + r * r / np.mean(r * r))
    assert density.keys() == set(x.index) and np.allclose([density[k] for k in x.index], total)


def test_density_of_samples_without_the_nodes(spark):
    cells = spark.createDataFrame([(1, 0, 2.0), (2, 9, 1.0)], "sample_id int, node_id int, x double")
    e = spark.createDataFrame([(0, 1, 0.5)], "src int, dst int, w double")
    got = dict(map(tuple, learner.log_density(cells, e, spark.createDataFrame([(1, 1.0)], "node_id int, variance double")).collect()))
    assert np.allclose([got[1], got[2]], [-0.5 * (np.log(2 * np.pi) + 1), -0.5 * np.log(2 * np.pi)])


def test_every_half_hour_ends_a_window(spark, tmp_path):
    r, start = np.random.default_rng(5), dt.datetime(2024, 1, 1)
    halves = [0, 1, 2, 30, 49, 50, 97]
    rows = [(i, start + dt.timedelta(minutes=30 * halves[i % 7] + 5), int(r.integers(70)), "error" if i % 3 == 0 else "view", 1.0, f'{{"k": {r.integers(100)}}}') for i in range(140)]
    spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    x = np.zeros((140, 31))
    for i, (_, _, user, kind, _, props) in enumerate(rows):
        k = int(props[6:-1])
        x[i, [4 + user % 10, 14 + k // 10, 24 + user % 7] + ([k // 25] if kind == "error" else [])] = 1
    at, first = np.array([halves[i % 7] for i in range(140)]), int(dt.datetime(2024, 1, 1, tzinfo=dt.UTC).timestamp()) // 1800
    sums = {h: x[(at > h - 48) & (at <= h)] for h in halves}
    want = {(first + h, a, b): (m.T @ m)[a, b] for h, m in sums.items() for a in range(31) for b in range(a, 31) if (m.T @ m)[a, b]}
    assert {(q["end"], q["a"], q["b"]): q["s"] for q in workloads.queries()["moments_windows"](spark, str(tmp_path)).collect()} == want

    got = {(q["end"], q["src"], q["dst"]): q["w"] for q in workloads.queries()["fit_windows"](spark, str(tmp_path)).collect()}
    assert {k[0] for k in got} == {first + h for h in halves}
    p = learner.LearnerParams(lam=0.02)
    for h, m in sums.items():
        w, trace, _ = learner.fit_dense(m.T @ m / len(m), p)
        assert min(trace[-1]["bound"], trace[-1]["trexp"]) <= p.eps
        assert {k[1:] for k in got if k[0] == first + h} == set(zip(*np.nonzero(np.abs(w) >= 0.05), strict=True))


def test_all_embedding_dimensions(spark, sf):
    x = np.array([r["embedding"] for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("embedding").collect()], dtype=float)
    got = {(r["a"], r["b"]): r["c"] for r in workloads.queries()["moments_vectors"](spark, sf).collect()}
    assert got.keys() == {(a, b) for a in range(64) for b in range(a, 64)}
    c = x.T @ x / len(x)
    assert all(abs(v - c[k]) < 1e-5 for k, v in got.items())


def test_all_dimensions_are_planted_and_learnt(spark, sf):
    assert {(r["d"], r["true"]) for r in workloads.queries()["fit_gene_stand_in"](spark, sf).collect()} == {(64, 122)}


def test_every_oracle_is_sql():
    import __spark_entry__ as entry

    assert all(isinstance(v, str) for v in entry.oracle_sql().values())
