"""Screening and moments of listed pairs without a table of all pairs, against that table."""

import numpy as np
import pytest

from dagframe import workloads
from dagframe.operators import learner, moments, neighbours
from dagframe.operators import workload_frames as base
from dagframe.operators import workload_learning as learning


def held(frame, *names):
    return {tuple(r[n] for n in names[:-1]): r[names[-1]] for r in frame.collect()}


@pytest.mark.parametrize("small", [False, True])
def test_equal_to_all_pairs(spark, monkeypatch, small):
    if small:  # many blocks, few pairs at a time
        monkeypatch.setattr(neighbours, "OWN", 40)
        monkeypatch.setattr(neighbours, "PAIRS", 200)
    r = np.random.default_rng(3)
    rows = [(s, int(n), float(r.normal()) if s % 3 else 1.0) for s in range(120) for n in r.choice(90, r.integers(1, 30), replace=False) if n != 5]
    cells = spark.createDataFrame(rows, "sample_id int, node_id int, x double")
    m, samples = moments.from_cells(cells), neighbours.Samples(cells, 90)
    assert samples.fits()
    want, got = (held(f, "src", "dst", "w") for f in (learning._screened_start(m, 4), neighbours.strongest(samples, 4)))
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)
    start = learning._screened_start(m, 4)
    want = held(learner.support_moments(m, start), "a", "b", "c")
    got = held(samples.own().unionByName(neighbours.listed(samples, learner.support_pairs(start))), "a", "b", "c")
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in want)


def test_samples_too_long_for_a_task_take_the_other_way(spark, sf, monkeypatch):
    cells = base.ratings(spark, sf, "part")
    want = learning._screened_fit(cells, 201).drop("seconds").collect()
    monkeypatch.setattr(neighbours, "HELD", 1)
    got = learning._screened_fit(cells, 201).drop("seconds").collect()
    assert len(got) == len(want) and all(abs(a["loss"] - b["loss"]) < 1e-6 and a["nnz"] == b["nnz"] for a, b in zip(got, want, strict=True))


def test_large_graphs_list_no_table_of_pairs(spark, sf, monkeypatch):
    monkeypatch.setattr(moments, "from_cells", None)
    for name in ("part_graph_trace", "token_graph_trace"):
        assert workloads.queries()[name](spark, sf).count()


def test_words_of_unique_documents_are_counted_without_a_shuffle_of_words(spark):
    from dagframe.operators import matrices

    docs = spark.createDataFrame([(i, " ".join(f"w{j}" for j in range(i % 7)) + " w0") for i in range(40)], "doc_id int, text string")
    labels = matrices.tokens(docs)
    a, b = (held(matrices.dictionary(labels, "token", 5, once=x), "node_id", "label", "support") for x in (True, False))
    assert a == b and len(a) == 6
    repeated = labels.unionByName(labels)
    assert held(matrices.dictionary(repeated, "token", 5), "node_id", "label", "support") == a
