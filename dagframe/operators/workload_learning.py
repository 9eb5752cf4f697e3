"""Queries on sample matrices, losses, learning steps, whole learning runs and recommendation."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from dagframe.functions.columns import stable
from dagframe.operators import baseline, batches, bound, grid, learner, loss, matrices, metrics, moments, neighbours, optim, recommend
from dagframe.operators import workload_frames as base
from dagframe.plans import sqlgen
from dagframe.plans.lineage import cut
from dagframe.sources.tables import table

LAM, N_STEPS, RHO, ETA = 0.1, 3, 1.0, 1.0


def _moments(s, d) -> DataFrame:
    return cut(moments.from_wide(base.numerics(s, d), base.NUMERIC))


def _long_numerics(s, d) -> tuple[DataFrame, int]:
    wide = cut(base.numerics(s, d).withColumn("sample_id", F.monotonically_increasing_id()))
    return matrices.long_of(wide, "sample_id", base.NUMERIC), wide.count()


def _loss_samples(s, d):
    cells, n = _long_numerics(s, d)
    return loss.from_samples(cells, base.probe(s), n, LAM).select(*[stable(c).alias(c) for c in ("fit", "penalty", "loss")])


def _loss_moments(s, d):
    return loss.from_moments(_moments(s, d), base.probe(s), LAM).select(*[stable(c).alias(c) for c in ("fit", "penalty", "loss")])


def _gradient_samples(s, d):
    cells, n = _long_numerics(s, d)
    return loss.gradient_from_samples(cells, base.probe(s), n, LAM).select("src", "dst", stable("g").alias("g"))


def _augmented(s, d):
    m, e = _moments(s, d), base.probe(s)
    row = loss.from_moments(m, e, LAM).select("loss").crossJoin(bound.spectral_bound(e, 1))  # one row each
    both = loss.gradient_from_moments(m, e, LAM).select("src", "dst", F.col("g").alias("gl")).join(bound.bound_gradient(e, 1).select("src", "dst", F.col("g").alias("gb")), ["src", "dst"])
    return learner.augmented(both.crossJoin(F.broadcast(row)), RHO, ETA).select("src", "dst", stable("objective").alias("objective"), stable("g").alias("g"))


def _adam(s, d):
    e = base.probe(s)
    g = loss.gradient_from_moments(_moments(s, d), e, LAM)
    return optim.adam(optim.start(e), g, 1).select("src", "dst", *[stable(c).alias(c) for c in ("w", "m1", "m2")])


def _three_steps(s, d):
    p = learner.LearnerParams(lam=LAM, k=1)
    return learner.inner(base.probe(s), _moments(s, d), p, RHO, ETA, N_STEPS).select("src", "dst", stable("w").alias("w"))


BATCH = 300


def _batched_steps(s, d):
    """Three steps of brand ratings, each on another mini-batch of customers."""
    cells = _ratings(s, d)
    n = cells.select("sample_id").distinct().count()
    p = learner.LearnerParams(lam=LAM, k=1, batch=BATCH)
    return learner.inner(base.brand_probe(s), None, p, RHO, ETA, N_STEPS, cells, n).select("src", "dst", stable("w").alias("w"))


def _fit_batched(s, d):
    """Brand graph learnt from mini-batches of customers, with a small-weight filter."""
    cells = _ratings(s, d)
    e, _ = learner.fit(moments.from_cells(cells), 56, learner.LearnerParams(t_outer=4, t_inner=100, batch=BATCH, theta=1e-3), "dense", cells=cells)
    return learner.extract_graph(e, 0.01)


def _proximal(s, d):
    g = loss.gradient_from_moments(_moments(s, d), base.probe(s), 0.0)
    return optim.proximal(base.probe(s), g, 0.01, LAM).select("src", "dst", stable("w").alias("w"))


def _nll(s, d):
    m, e = _moments(s, d), base.probe(s)
    each = loss.neg_log_likelihood(m, e, 1000).select(F.lit("each").alias("variance"), stable("nll", 4).alias("nll"))
    return each.unionByName(loss.neg_log_likelihood(m, e, 1000, True).select(F.lit("equal").alias("variance"), stable("nll", 4).alias("nll")))


def _ratings(s, d) -> DataFrame:
    return cut(base.ratings(s, d))


def _rating_moments(s, d) -> DataFrame:
    return moments.from_cells(_ratings(s, d))


def _links(s, d) -> DataFrame:
    """Links of brands for recommendation: the moments of centred ratings, from the smaller to the larger number."""
    return cut(_rating_moments(s, d).where("a <> b").select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("c").alias("w")))


def _brand_nodes(s, d) -> DataFrame:
    return table(s, d, "part").select(base.brand().alias("node_id"), F.col("p_brand").alias("label")).distinct()


def _popularity(s, d) -> DataFrame:
    return _ratings(s, d).groupBy("node_id").agg(F.countDistinct("sample_id").alias("popularity"))


def _batch(s, d):
    cells = base.ratings(s, d)
    chosen = batches.draw_exact(cells, 20, 7, 0)
    return cells.join(chosen, "sample_id", "left_semi").groupBy("sample_id").agg(F.count("*").alias("n"))


def _indicators_documents(s, d):
    docs = table(s, d, "documents").select("doc_id", "lang", "source", F.concat(F.lit("z"), F.floor(F.log10(F.greatest("n_chars", F.lit(1)))).cast("string")).alias("size"))
    cells, nodes = matrices.indicators(docs, "doc_id", {"lang": "lang", "source": "source", "size": "size"})
    return cells.join(nodes.select("node_id", "label"), "node_id").groupBy("node_id", "label").agg(F.count("*").alias("n"))


def _mixed(s, d):
    lang = matrices.indicators(table(s, d, "documents"), "doc_id", {"lang": "lang"})
    lab = matrices.indicators(table(s, d, "labels"), "doc_id", {"quality": "quality", "toxic": "toxic"})
    cells, nodes = matrices.union_nodes(lang, lab)
    return cells.join(nodes, "node_id").groupBy("node_id", "label").agg(F.count("*").alias("n"))


def _tokens(s, d):
    labels = matrices.tokens(table(s, d, "documents"))
    return matrices.dictionary(labels, "token", 5).agg(F.count("*").alias("n_nodes"), F.sum("support").alias("cells"), F.max("support").alias("top"))


def _embedding_moments(s, d):
    return moments.from_vectors(table(s, d, "embeddings"), "embedding").select("a", "b", stable("c").alias("c"))


def _refit(s, d):
    e = s.createDataFrame([(0, 1), (6, 1), (5, 6), (1, 4)], "src int, dst int")
    return learner.refit(_moments(s, d), e).select("src", "dst", stable("w").alias("w"), stable("variance").alias("variance"))


#: Planted experiments: two topologies, three noises, replicates by seed; samples are ten a node. The penalty starts low, so that
#: the fit settles before cycles are forced out; a low start was first tried on seeds 1 to 3, its values were chosen on 11 to 14.
GRAPHS, NOISES, NODES, SEEDS = ("er", "sf"), ("gauss", "exp", "gumbel"), (10, 20), (1, 2, 3, 4, 5)
PLANTED = learner.LearnerParams(t_outer=100, t_inner=300, lam=0.1, eps=1e-4, rho0=0.03, eta0=0.0)
_held: dict = {}


def _once(s, name: str, make) -> DataFrame:
    """A result that many queries read: made once in an application, kept behind a checkpoint."""
    key = (s.sparkContext.applicationId, name)
    if key not in _held:
        _held[key] = cut(make())
    return _held[key]


def _planted_results(s) -> DataFrame:
    """Every cell of the experiments by the bound and by the exponential trace, at every stop tolerance and filter."""
    cells = [(g, n, d, seed, m) for g in GRAPHS for n in NOISES for d in NODES for seed in SEEDS for m in ("bound", "trexp")]
    return _once(s, "planted", lambda: baseline.planted_runs(s, cells, PLANTED))


def _planted_best(s) -> DataFrame:
    return grid.best_cell(_planted_results(s), "graph", "noise", "d", "seed", "method")


def _planted_traces(s) -> DataFrame:
    cells = [(g, n, 10, seed, "bound") for g in GRAPHS for n in NOISES for seed in SEEDS]
    return _once(s, "traces", lambda: baseline.planted_traces(s, cells, PLANTED))


def _line_noise(s, d, seeds: tuple[int, ...], nodes: int) -> dict:
    """Noise of planted experiments from all given lines, dealt to the replicates by order: places from keys and quantities, steps from prices in cents."""
    mod = lambda c, n: F.pmod(c.cast("long"), F.lit(n))
    place = mod(F.col("l_partkey") * 7919 + F.col("l_suppkey") * 31 + F.col("l_quantity"), baseline.PLACES)
    lines = table(s, d, "lineitem").select(place.alias("place"), mod(F.round(F.col("l_extendedprice") * 100), baseline.PLACES).alias("step"), (mod(F.col("l_orderkey"), len(seeds)) + min(seeds)).alias("seed"))
    return baseline.given_noise(lines, nodes)


def _given_cells(given: dict, cells: list) -> list:
    """The runs whose replicates have samples."""
    return [c for c in cells if given.get((c[1], c[3]), (0,))[0] > 1]


def _given_best(s, d) -> DataFrame:
    """The planted experiments with noise of the given lines."""

    def make() -> DataFrame:
        given = _line_noise(s, d, SEEDS, max(NODES))
        return baseline.planted_runs(s, _given_cells(given, [(g, n, k, seed, m) for g in GRAPHS for n in NOISES for k in NODES for seed in SEEDS for m in ("bound", "trexp")]), PLANTED, given=given)

    return grid.best_cell(_once(s, f"given {d}", make), "graph", "noise", "d", "seed", "method")


def _fit_planted(s, d):
    """Bound against the exact measure on planted graphs: F1, distance, correlation and seconds by method."""
    return grid.summarise(_planted_best(s), "graph", "noise", "d", "method", measures=("f1", "shd", "corr", "seconds"))


def _planted_grid(s, d):
    """Mean F1 and distance of each stop tolerance and filter over all runs of a method."""
    return grid.summarise(_planted_results(s), "method", "eps", "tau")


def _planted_audit(s, d):
    """Design rules along the traces of runs on noise of the given lines: does the bound stay on the safe side of the trace, and how closely do they move."""
    given = _line_noise(s, d, SEEDS, 10)
    cells = _given_cells(given, [(g, n, 10, seed, "bound") for g in GRAPHS for n in NOISES for seed in SEEDS])
    return metrics.audit_constraint(cut(baseline.planted_traces(s, cells, PLANTED, given)), 1e-2, 10)


def _part_edges(s, d, nodes: int) -> DataFrame:
    """EDGES that the given parts' keys, sizes and prices make among some nodes; weights within 0.1 of zero, of a pair that of its lowest key."""
    key = F.col("p_partkey")
    at = lambda c: F.pmod(c, F.lit(nodes)).cast("int")
    w = F.pmod(F.round(F.col("p_retailprice") * 100).cast("long") * 7919, F.lit(2001)) / 10000 - 0.1
    edges = table(s, d, "part").select("p_partkey", at(key).alias("src"), at(key * 31 + F.col("p_size") * 977).alias("dst"), w.alias("w")).where("src <> dst")
    return edges.groupBy("src", "dst").agg(F.min_by("w", "p_partkey").alias("w"), F.min("p_partkey").alias("key"))


def _constraint_costs(s, d):
    """The four constraint functions on the same graphs of given parts: error of the gradient against differences, seconds, growth
    of seconds with nodes, and what an acyclic graph gives."""
    import time

    def weights(n: int, most: int) -> np.ndarray:
        """Weights of the ``most`` pairs with the lowest keys, of all that the given parts make."""
        w, e = np.zeros((n, n)), learner.within(_part_edges(s, d, n).orderBy("key").limit(most), learner.LOCAL_ROWS)
        w[e["src"].to_numpy(), e["dst"].to_numpy()] = 4 * e["w"].to_numpy()
        return w

    small, large = weights(12, 132), [weights(n, 2 * n) for n in (100, 400)]
    order = np.triu(small, 1)
    rows = []
    for name in ("bound", "trexp", "trpow", "radius"):
        f, took = learner.constraint_of(learner.LearnerParams(constraint=name)), []
        w = small
        g, h, worst = f(w)[1], 1e-6, 0.0
        live = np.argwhere(np.abs(w) > 0.05)
        for i, j in live[[0, len(live) // 2, -1]]:
            up, low = w.copy(), w.copy()
            up[i, j] += h
            low[i, j] -= h
            worst = max(worst, abs((f(up)[0] - f(low)[0]) / (2 * h) - g[i, j]) / max(1e-9, abs(g[i, j])))
        for x in large:
            f(x)
            t = time.perf_counter()
            f(x)
            took.append(time.perf_counter() - t)
        rows.append((name, float(worst), took[0], took[1], float(np.log(took[1] / took[0]) / np.log(4)), float(f(order)[0])))
    return s.createDataFrame(rows, "constraint string, gradient_error double, seconds_100 double, seconds_400 double, growth double, of_acyclic double")


def _planted_seconds(s, d):
    """Whole runs to the same tolerance, by nodes: seconds of the bound and of the exponential trace."""
    cells = [("er", "gauss", n, 1, m) for n in (10, 20, 50, 100) for m in ("bound", "trexp")]
    p = learner.LearnerParams(t_outer=30, lam=0.1, eps=1e-4, stop_on="trexp")
    runs = baseline.planted_runs(s, cells, p, (1e-4,), (0.3,))
    return metrics.speedup(runs, "trexp", "bound", "d")


def _baseline_planted(s, d):
    given = _line_noise(s, d, (1, 2), 10)
    cells = _given_cells(given, [(g, "gauss", 10, seed, m) for g in GRAPHS for seed in (1, 2) for m in ("trpow", "radius", "climb", "correlation")])
    best = grid.best_cell(cut(baseline.planted_runs(s, cells, learner.LearnerParams(t_outer=20), given=given)), "graph", "noise", "d", "seed", "method")
    return grid.summarise(best, "graph", "noise", "d", "method")


def _fit_brand(s, d):
    e, _ = learner.fit(_rating_moments(s, d), 56, learner.LearnerParams(t_outer=4, t_inner=100), "dense")
    return learner.extract_graph(e, 0.01)


def _learnt_links(s, d) -> DataFrame:
    """Links of brands from the learner's graph of centred ratings."""
    return _once(s, f"links {d}", lambda: learner.extract_graph(learner.fit(_rating_moments(s, d), 56, learner.LearnerParams(t_outer=30, t_inner=100, lam=0.05), "dense")[0], 0.01))


def _fit_trace(s, d):
    """Trace of a screened sparse run on brand ratings."""
    m = _rating_moments(s, d)
    top = baseline.correlation_graph(m, 120).select(F.col("a").alias("src"), F.col("b").alias("dst"), (F.col("r") / 2).alias("w"))
    start = top.unionByName(top.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return learner.fit(m, 56, learner.LearnerParams(t_outer=60, t_inner=100, theta=1e-3), "local_sparse", start)[1]


def _gene(s, d):
    """Embedding dimensions as variables with planted effects: what the learner and the correlation graph recover."""
    n_dims = 64
    wide = table(s, d, "embeddings").select(*[F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(n_dims)])
    std = matrices.standardise(wide, [f"x{i}" for i in range(n_dims)])
    effects = [(f"x{i}", f"x{i + k}", 0.8 if (i + k) % 2 else -0.7) for i in range(n_dims) for k in (1, 5) if i + k < n_dims]
    from dagframe.operators import simulate

    truth = s.createDataFrame([(int(a[1:]), int(b[1:])) for a, b, _ in effects], "src int, dst int")
    planted = cut(std)
    for at in range(0, len(effects), 16):  # columns nest in one another, so a plan of all effects grows too large
        planted = cut(simulate.plant(planted, effects[at : at + 16]))
    m = cut(moments.from_vectors(planted.select(F.array(*[f"x{i}" for i in range(n_dims)]).alias("x")), "x"))  # 2,080 pairs: one matrix product, not as many aggregates
    got = learner.extract_graph(learner.fit(m, n_dims, learner.LearnerParams(t_outer=20), "dense")[0], 0.3)
    cor = baseline.correlation_graph(m, truth.count()).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("r").alias("w"))
    one = lambda g, name: metrics.measures(metrics.edge_confusion(truth, g).withColumn("d", F.lit(n_dims))).withColumn("method", F.lit(name))
    return one(got, "bound").unionByName(one(cor, "correlation"))


#: Regulators of the planted network, and what the learner starts from.
REGULATORS = 8
GENES = learner.LearnerParams(t_outer=60, t_inner=300, lam=0.1, eps=1e-4, rho0=0.03, eta0=0.0)


def _gene_networks(s, d):
    """A planted regulatory network on all embedding dimensions: eight regulators in a tree, every other dimension under two of
    them. Counts, measures and AUC of the bound, the exponential trace and the correlation graph."""
    n_dims = 64
    tree = [((i - 1) // 2, i, 0.6) for i in range(1, REGULATORS)]
    under = [(r, i, w) for i in range(REGULATORS, n_dims) for r, w in ((i % REGULATORS, 0.8), ((i + 1 + i // REGULATORS % 6) % REGULATORS, -0.7))]
    wide = table(s, d, "embeddings").select(*[F.col("embedding")[i].cast("double").alias(f"x{i}") for i in range(n_dims)])
    std = matrices.standardise(wide, [f"x{i}" for i in range(n_dims)])
    from dagframe.operators import simulate

    named = lambda effects: [(f"x{a}", f"x{b}", w) for a, b, w in effects]
    planted = simulate.plant(cut(simulate.plant(std, named(tree))), named(under))
    m = cut(moments.from_vectors(planted.select(F.array(*[f"x{i}" for i in range(n_dims)]).alias("x")), "x"))
    truth = s.createDataFrame([(a, b) for a, b, _ in tree + under], "src int, dst int")
    cor = baseline.correlation_graph(m, len(tree) + len(under)).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("r").alias("w"))
    out = None
    for name, e in (("bound", learner.fit(m, n_dims, GENES, "dense")[0]), ("trexp", baseline.fit_trexp(m, n_dims, GENES)[0]), ("correlation", cor)):
        found = metrics.measures(metrics.edge_confusion(truth, learner.extract_graph(e, 0.3) if name != "correlation" else e).withColumn("d", F.lit(n_dims)))
        one = found.crossJoin(metrics.roc_auc(truth, e, n_dims)).withColumn("method", F.lit(name))  # one row each
        out = one if out is None else out.unionByName(one)
    return out


def _wide_graph(s, d):
    """Seconds of the bound and its gradient on EDGES of 160,000 nodes made as tables, up to five million edges."""
    import time

    from dagframe.operators.bound_local import value_and_grad

    rows, n = [], 160_000
    for edges in (500_000, 5_000_000):
        got = learner.within(learner.init_edges(s, n, edges / n**2, 3), learner.LOCAL_ROWS)
        src, dst, w = (got[k].to_numpy() for k in ("src", "dst", "w"))
        t = time.perf_counter()
        value, grad = value_and_grad(src.astype(np.int64), dst.astype(np.int64), w, n)
        rows.append((len(w), float(value), float(np.abs(grad).max()), time.perf_counter() - t))
    return s.createDataFrame(rows, "edges long, bound double, steepest double, seconds double")


def _line_edges(s, d, nodes: int, most: int) -> DataFrame:
    """The ``most`` EDGES that come first by hash, of all that the given lines make among some nodes: a line is a cycle from its order
    to its part, on to its supplier and back. Weights within 0.1 of zero by price, of a pair the least."""
    at = lambda kind, c: F.pmod(F.xxhash64(F.lit(kind), c), F.lit(nodes)).cast("int")
    ends = [at(c, F.col(c)) for c in ("l_orderkey", "l_partkey", "l_suppkey")]
    w = F.pmod(F.round(F.col("l_extendedprice") * 100).cast("long") * 7919, F.lit(2001)) / 10000 - 0.1
    sides = F.array(*[F.struct(a.alias("src"), b.alias("dst")) for a, b in zip(ends, ends[1:] + ends[:1], strict=True)])
    given = table(s, d, "lineitem").where("l_extendedprice is not null").select(w.alias("w"), F.explode(sides).alias("e")).select("e.src", "e.dst", "w").where("src <> dst")
    edges = given.withColumn("nth", F.pmod(F.xxhash64("src", "dst"), F.lit(1 << 40)))
    share = min(1.0, 1.5 * most / max(1, 3 * table(s, d, "lineitem").count()))
    while True:  # the first by hash are the same however many pairs are compared; most of a large table need not be
        found = cut(edges.where(F.col("nth") < int(share * (1 << 40))).groupBy("src", "dst", "nth").agg(F.min("w").alias("w")))
        if share >= 1 or found.count() >= most:
            return found.orderBy("nth", "src", "dst").limit(most).select("src", "dst", "w")
        share = min(1.0, 4 * share)


def _scaling(s, d):
    """Seconds of the bound and its gradient in one process, for growing edge numbers among 160,000 nodes, edges of the given lines;
    fewer where these make fewer."""
    import time

    from dagframe.operators.bound_local import value_and_grad

    rows, sizes = [], (10_000, 100_000, 1_000_000)
    all_ = learner.within(_line_edges(s, d, 160_000, sizes[-1]), learner.LOCAL_ROWS)
    src, dst, w = (all_[k].to_numpy() for k in ("src", "dst", "w"))
    for n in (min(size, len(w)) for size in sizes):
        t = time.perf_counter()
        value, _ = value_and_grad(src[:n].astype(np.int64), dst[:n].astype(np.int64), w[:n], 160_000)
        rows.append((n, float(value), time.perf_counter() - t))
    return s.createDataFrame(rows, "edges long, bound double, seconds double")


def _nodes_scaling(s, d):
    """Seconds of a value and gradient by the number of nodes, two edges a node: the bound against the exponential trace."""
    import time

    from dagframe.operators.bound_local import value_and_grad

    rows, r = [], np.random.default_rng(1)
    for n in (10, 20, 50, 100, 200, 500):
        src, dst, w = r.integers(n, size=2 * n), r.integers(n, size=2 * n), r.uniform(-0.5, 0.5, 2 * n)
        full = np.zeros((n, n))
        full[src, dst] = w
        took = []
        for f in (lambda src=src, dst=dst, w=w, n=n: value_and_grad(src, dst, w, n), lambda full=full: learner.trexp_dense(full)):
            f()
            t = time.perf_counter()
            for _ in range(5):
                f()
            took.append((time.perf_counter() - t) / 5)
        rows.append((n, took[0], took[1], took[1] / took[0]))
    return s.createDataFrame(rows, "d int, bound_seconds double, trexp_seconds double, speedup double")


def _screened_start(m: DataFrame, parents: int) -> DataFrame:
    """EDGES into each node from the ``parents`` nodes that correlate most with it, at half the correlation, in both directions of a pair where both choose it."""
    own = m.where("a = b")
    at = lambda end: own.select(F.col("a").alias(end), F.col("c").alias(f"v_{end}"))
    r = m.where("a <> b").join(at("a"), "a").join(at("b"), "b").select("a", "b", (F.col("c") / F.sqrt(F.col("v_a") * F.col("v_b"))).alias("r"))
    both = r.select(F.col("a").alias("src"), F.col("b").alias("dst"), "r").unionByName(r.select(F.col("b").alias("src"), F.col("a").alias("dst"), "r"))
    nth = F.row_number().over(Window.partitionBy("dst").orderBy(F.desc(F.abs("r")), "src"))
    return both.withColumn("nth", nth).where(F.col("nth") <= parents).select("src", "dst", (F.col("r") / 2).alias("w"))


#: Settings of runs on large graphs: a small filter, and the exponential trace as the measure that ends them.
LARGE = learner.LearnerParams(t_outer=40, t_inner=60, lam=0.01, theta=1e-3, eps=1e-8, stop_on="trexp", screen=5)


def _screened_fit(cells: DataFrame, nodes: int, n: int | None = None) -> DataFrame:
    """Trace of a sparse run with ``LARGE`` on the support that ``_screened_start`` gives; pairs are never all listed where a task
    can hold the samples of some nodes."""
    samples = neighbours.Samples(cells, nodes, n)
    if not samples.fits():
        m = cut(moments.from_cells(cells, samples.n))
        return learner.fit(m, nodes, LARGE, "local_sparse", _screened_start(m, LARGE.screen))[1]
    start = cut(neighbours.strongest(samples, LARGE.screen))
    m = samples.own().unionByName(neighbours.listed(samples, learner.support_pairs(start)))
    return learner.fit(m, nodes, LARGE, "local_sparse", start, listed=True)[1]


def _token_graph(s, d):
    """Trace of a sparse run on all words that at least five documents hold, from moments of words that occur together; the support
    is each word's most correlated others (``screen``)."""
    docs = table(s, d, "documents")
    total, labels = docs.count(), matrices.tokens(docs)
    once = docs.select("doc_id").distinct().count() == total  # words of a row are distinct already
    nodes = cut(matrices.dictionary(labels, "token", 5, once=once))
    n = nodes.count()
    number = nodes.select("label", "node_id")
    cells = labels.join(F.broadcast(number) if n <= 500_000 else number, "label").select("sample_id", "node_id", F.lit(1.0).alias("x"))
    return _screened_fit(cells if once else cells.distinct(), n, total)


def _fit_parts(s, d):
    """Trace of a sparse run on ratings with parts as nodes."""
    return _screened_fit(base.ratings(s, d, "part"), table(s, d, "part").agg(F.max("p_partkey")).first()[0] + 1)


def _distributed(s, d):
    """Trace of a short run whose edges and state stay tables."""
    return learner.fit(_moments(s, d), 8, learner.LearnerParams(t_outer=1, t_inner=2, k=1), "distributed", base.probe(s))[1].drop("trexp")


#: Effects added to the numeric columns, whose own correlations are nil: (cause, effect, weight).
EFFECTS = [("l_quantity", "l_extendedprice", 0.9), ("l_extendedprice", "l_discount", -0.7), ("l_tax", "l_discount", 0.6), ("l_discount", "o_totalprice", 0.8), ("p_size", "p_retailprice", 1.2), ("l_tax", "c_acctbal", -0.5)]


def _planted_numerics(s, d) -> DataFrame:
    """Moments of the numeric columns with ``EFFECTS`` planted."""
    from dagframe.operators import simulate

    return cut(moments.from_wide(simulate.plant(base.numerics(s, d), EFFECTS), base.NUMERIC))


def _lines(s, d) -> int:
    return table(s, d, "lineitem").count()


def _effect_edges(s) -> DataFrame:
    at = base.NUMERIC.index
    return s.createDataFrame([(at(a), at(b)) for a, b, _ in EFFECTS], "src int, dst int")


def _planted_search(s, d):
    """What greedy search, the exact measure, the bound and the correlation graph recover of the planted effects."""
    m, truth = _planted_numerics(s, d), _effect_edges(s)
    p = learner.LearnerParams(t_outer=20, lam=0.05)
    found = {
        "climb": baseline.hill_climb(m, 8, _lines(s, d), 3),
        "trexp": learner.threshold(learner.solve(m, 8, "exact", p), 0.3),
        "bound": learner.threshold(learner.solve(m, 8, "bound", p), 0.3),
        "correlation": baseline.correlation_graph(m, len(EFFECTS)).select(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("r").alias("w")),
    }
    out = None
    for name, e in found.items():
        one = metrics.measures(metrics.edge_confusion(truth, e).withColumn("d", F.lit(8))).withColumn("method", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


def _paradigms(s, d):
    """Edges on four planted columns by search, by the exact measure and by the bound."""
    m = cut(_planted_numerics(s, d).where("a < 4 and b < 4"))
    out = None
    for name in ("search", "exact", "bound"):
        options = {"n": _lines(s, d)} if name == "search" else {}
        one = learner.threshold(learner.solve(m, 4, name, learner.LearnerParams(t_outer=20, lam=0.05), **options), 0.3).select(F.lit(name).alias("paradigm"), "src", "dst")
        out = one if out is None else out.unionByName(one)
    return out


def _density(s, d):
    """Log density of each customer's ratings under a two-parent network of brands."""
    m, cells = _rating_moments(s, d), _ratings(s, d)
    e = _links(s, d).where("src <= 12 and dst between 13 and 15").select("src", "dst")
    fitted = cut(learner.refit(m, e))
    variance = fitted.select(F.col("dst").alias("node_id"), "variance").distinct()
    return learner.log_density(cells, fitted.select("src", "dst", "w"), variance)


def _alphas(s, d):
    return s.createDataFrame([(name, float(bound.suggest_alpha(g))) for name, g in (("sequence", base.order_sequence(s, d)), ("flow", base.net_flow(s, d)))], "graph string, alpha double")


def queries() -> dict:
    return {
        "moments_numeric": lambda s, d: moments.from_wide(base.numerics(s, d), base.NUMERIC).select("a", "b", stable("c").alias("c")),
        "moments_sparse": lambda s, d: _rating_moments(s, d).select("a", "b", stable("c").alias("c")),
        "moments_vectors": _embedding_moments,
        "standardised_columns": lambda s, d: base.numerics(s, d).agg(*[stable(F.sum(F.abs(c)), 3).alias(c) for c in base.NUMERIC]),
        "loss_samples": _loss_samples, "loss_moments": _loss_moments,
        "loss_per_node": lambda s, d: loss.per_node(_moments(s, d), base.probe(s)).select("node", stable("fit").alias("fit")),
        "loss_gradient": lambda s, d: loss.gradient_from_moments(_moments(s, d), base.probe(s), LAM).select("src", "dst", stable("g").alias("g")),
        "loss_gradient_samples": _gradient_samples,
        "nll_loss": _nll,
        "augmented_objective": _augmented,
        "adam_one_step": _adam, "inner_three_steps": _three_steps, "inner_batched_steps": _batched_steps, "fit_batched": _fit_batched, "proximal_step": _proximal,
        "threshold_theta": lambda s, d: learner.threshold(base.order_sequence(s, d), 0.4).select("src", "dst", stable("w").alias("w")),
        "minibatch_draw": _batch,
        "ratings_centred": lambda s, d: base.ratings(s, d).select("sample_id", "node_id", stable("x").alias("x")),
        "indicators_documents": _indicators_documents,
        "tokens_dictionary": _tokens,
        "mixed_nodes": _mixed,
        "embeddings_long": lambda s, d: matrices.from_arrays(table(s, d, "embeddings"), "vec_id", "embedding").groupBy("node_id").agg(stable(F.sum("x"), 4).alias("total"), F.count("*").alias("n")),
        "correlation_graph": lambda s, d: baseline.correlation_graph(_rating_moments(s, d), 15).select("a", "b", stable("r").alias("r")),
        "refit_two_parents": _refit,
        "top_links": lambda s, d: recommend.top_links(_links(s, d), _brand_nodes(s, d)).select("src", "src_label", "dst", "dst_label", stable("w").alias("w")),
        "propagate_scores": lambda s, d: recommend.score(_ratings(s, d), _links(s, d)).select("sample_id", "node_id", stable("score", 4).alias("score")),
        "explain_scores": lambda s, d: recommend.explain(_ratings(s, d), _links(s, d), 2).select("sample_id", "node_id", "nth", "via", stable("part", 4).alias("part")),
        "ego_graph": lambda s, d: recommend.ego_graph(_links(s, d).where("w > 0"), 11, 1).select("src", "dst", stable("w").alias("w"), "sign"),
        "degree_profile": lambda s, d: recommend.degree_profile(_links(s, d).where("w > 0"), _popularity(s, d)),
        "fit_planted": _fit_planted, "planted_grid": _planted_grid, "constraint_audit": _planted_audit, "constraint_costs": _constraint_costs, "planted_seconds": _planted_seconds,
        "replicate_summary": lambda s, d: grid.summarise(_planted_best(s), "graph", "noise", "method"),
        "cube_results": lambda s, d: grid.cube(_given_best(s, d), "graph", "noise", "method"),
        "speedup_table": lambda s, d: metrics.speedup(_planted_best(s), "trexp", "bound", "graph", "noise", "d"),
        "trace_correlation": lambda s, d: metrics.trace_correlation(_planted_traces(s), "graph", "noise", "seed"),
        "grid_readout": lambda s, d: _planted_best(s).where("d = 10"),
        "baseline_planted": _baseline_planted, "fit_brand_graph": _fit_brand, "fit_sparse_trace": _fit_trace, "fit_gene_stand_in": _gene, "gene_networks": _gene_networks, "wide_graph": _wide_graph,
        "hill_climb": lambda s, d: baseline.hill_climb(_planted_numerics(s, d), 8, _lines(s, d), 3),
        "exhaustive_four": lambda s, d: baseline.exhaustive(_planted_numerics(s, d).where("a < 4 and b < 4"), 4, _lines(s, d)),
        "planted_search": _planted_search,
        "bound_scaling": _scaling, "nodes_scaling": _nodes_scaling, "token_graph_trace": _token_graph, "part_graph_trace": _fit_parts, "fit_distributed": _distributed, "solve_paradigms": _paradigms, "log_density": _density,
        "learnt_top_links": lambda s, d: recommend.top_links(_learnt_links(s, d), _brand_nodes(s, d)),
        "learnt_scores": lambda s, d: recommend.score(_ratings(s, d), _learnt_links(s, d)),
        "learnt_ego_graph": lambda s, d: recommend.ego_graph(_learnt_links(s, d), 11, 1),
        "learnt_degrees": lambda s, d: recommend.degree_profile(_learnt_links(s, d), _popularity(s, d)),
        "suggest_alpha": _alphas,
        "init_edges": lambda s, d: learner.init_edges(s, 2000, 1e-3, 7),
    }


def rating_moments_sql() -> sqlgen.Ctes:
    """``cells`` of centred brand ratings and their moments ``m``."""
    return base.ratings_sql().add("m", "SELECT a, b, s / (SELECT count(DISTINCT sample_id) FROM cells) AS c FROM (SELECT x.node_id AS a, y.node_id AS b, sum(x.x * y.x) AS s FROM cells x JOIN cells y ON x.sample_id = y.sample_id WHERE x.node_id <= y.node_id GROUP BY 1, 2)")


def links_sql() -> sqlgen.Ctes:
    """``cells`` and ``links`` of brands, as the recommendation queries use them."""
    return rating_moments_sql().add("links", "SELECT a AS src, b AS dst, c AS w FROM m WHERE a <> b")


def oracle_sql() -> dict[str, str]:
    num = base.numerics_sql
    r6 = lambda c, n=6: f"round({c}, {n}) + 0.0 AS {c}"
    probe = lambda: num().add("probe", base.PROBE_SQL)
    step = lambda lam=LAM: sqlgen.moment_loss(probe(), "moments", "probe", lam)
    total = f"SELECT round(f, 6) + 0.0 AS fit, round(p, 6) + 0.0 AS penalty, round(f + p, 6) + 0.0 AS loss FROM (SELECT (SELECT sum(fit) FROM fit) AS f, {LAM} * (SELECT sum(abs(w)) FROM probe) AS p)"
    aug = sqlgen.gradient(sqlgen.forward(step(), "probe", 1, 0.9), 1, 0.9)
    three = probe().add("e0", "SELECT src, dst, w, 0.0::DOUBLE AS m1, 0.0::DOUBLE AS m2 FROM probe")
    for t in range(1, N_STEPS + 1):
        three.add(f"w{t - 1}", f"SELECT src, dst, w FROM e{t - 1}")
        sqlgen.moment_loss(three, "moments", f"w{t - 1}", LAM, f"l{t}")
        sqlgen.gradient(sqlgen.forward(three, f"w{t - 1}", 1, 0.9, f"b{t}"), 1, 0.9, f"b{t}")
        three.add(f"g{t}", f"SELECT e.src, e.dst, e.w, e.m1, e.m2, a.g + ({ETA} + {RHO} * (SELECT sum(scale) FROM b{t}st1)) * b.g AS g FROM e{t - 1} e JOIN l{t}gl a USING (src, dst) JOIN b{t}grad b USING (src, dst)")
        three.add(f"n{t}", f"SELECT src, dst, w, 0.9 * m1 + 0.1 * g AS m1, 0.999 * m2 + 0.001 * g * g AS m2 FROM g{t}")
        three.add(f"e{t}", f"SELECT src, dst, w - 0.01 * (m1 / (1 - pow(0.9, {t}))) / (sqrt(m2 / (1 - pow(0.999, {t}))) + 1e-8) AS w, m1, m2 FROM n{t}")
    rat = base.ratings_sql
    batched = rat().add("b0", "SELECT src, dst, w, 0.0::DOUBLE AS m1, 0.0::DOUBLE AS m2 FROM (" + base.BRAND_PROBE_SQL + ")").add("per_", f"SELECT greatest(1, count(DISTINCT sample_id) // {BATCH})::BIGINT AS per FROM cells")
    for t in range(1, N_STEPS + 1):
        nth, epoch = f"({t - 1} % (SELECT per FROM per_))", f"({t - 1} // (SELECT per FROM per_))"
        batched.add(f"c{t}", f"SELECT * FROM cells WHERE ('0x' || substr(md5('7:' || {epoch} || ':' || sample_id), 1, 8))::BIGINT % (SELECT per FROM per_) = {nth}")
        batched.add(f"bm{t}", f"SELECT a, b, s / (SELECT count(DISTINCT sample_id) FROM c{t}) AS c FROM (SELECT x.node_id AS a, y.node_id AS b, sum(x.x * y.x) AS s FROM c{t} x JOIN c{t} y ON x.sample_id = y.sample_id WHERE x.node_id <= y.node_id GROUP BY 1, 2)")
        batched.add(f"w{t - 1}", f"SELECT src, dst, w FROM b{t - 1}")
        sqlgen.moment_loss(batched, f"bm{t}", f"w{t - 1}", LAM, f"l{t}")
        sqlgen.gradient(sqlgen.forward(batched, f"w{t - 1}", 1, 0.9, f"f{t}"), 1, 0.9, f"f{t}")
        batched.add(f"g{t}", f"SELECT e.src, e.dst, e.w, e.m1, e.m2, a.g + ({ETA} + {RHO} * (SELECT sum(scale) FROM f{t}st1)) * x.g AS g FROM b{t - 1} e JOIN l{t}gl a USING (src, dst) JOIN f{t}grad x USING (src, dst)")
        batched.add(f"n{t}", f"SELECT src, dst, w, 0.9 * m1 + 0.1 * g AS m1, 0.999 * m2 + 0.001 * g * g AS m2 FROM g{t}")
        batched.add(f"b{t}", f"SELECT src, dst, w - 0.01 * (m1 / (1 - pow(0.9, {t}))) / (sqrt(m2 / (1 - pow(0.999, {t}))) + 1e-8) AS w, m1, m2 FROM n{t}")
    rm, links = rating_moments_sql, links_sql
    nodes = f"SELECT DISTINCT {base.BRAND_SQL} AS node_id, p_brand AS label FROM part"
    const = 1 + 1.8378770664093453
    docs_ind = "SELECT doc_id, 'lang=' || lang AS label FROM documents UNION SELECT doc_id, 'source=' || source FROM documents UNION SELECT doc_id, 'size=z' || floor(log10(greatest(n_chars, 1)))::INTEGER FROM documents"
    mixed = "SELECT doc_id, 'lang=lang=' || lang AS label FROM documents UNION SELECT doc_id, 'quality=quality=' || quality FROM labels UNION SELECT doc_id, 'toxic=toxic=' || toxic FROM labels"
    numbered = lambda rows: f"SELECT (row_number() OVER (ORDER BY label) - 1)::INTEGER AS node_id, label, n FROM (SELECT label, count(*)::BIGINT AS n FROM ({rows}) WHERE label IS NOT NULL GROUP BY label)"
    return {
        "moments_numeric": num().then(f"SELECT a, b, {r6('c')} FROM moments"),
        "moments_sparse": rm().then(f"SELECT a, b, {r6('c')} FROM m"),
        "moments_vectors": "SELECT i AS a, j AS b, round(avg(embedding[i + 1]::DOUBLE * embedding[j + 1]::DOUBLE), 6) + 0.0 AS c FROM embeddings, (SELECT a.range::INTEGER AS i, b.range::INTEGER AS j FROM range(64) a, range(64) b WHERE a.range <= b.range) GROUP BY 1, 2",
        "standardised_columns": num().then("SELECT " + ", ".join(f"round(sum(abs(x{i})), 3) + 0.0 AS {c}" for i, c in enumerate(base.NUMERIC)) + " FROM std_"),
        "loss_samples": step().then(total), "loss_moments": step().then(total),
        "loss_per_node": step().then(f"SELECT node, {r6('fit')} FROM fit"),
        "loss_gradient": step().then(f"SELECT src, dst, {r6('g')} FROM gl"),
        "loss_gradient_samples": step().then(f"SELECT src, dst, {r6('g')} FROM gl"),
        "nll_loss": step().then(f"SELECT 'each' AS variance, round(500.0 * sum(ln(fit) + {const}), 4) + 0.0 AS nll FROM fit UNION ALL SELECT 'equal', round(500.0 * count(*) * (ln(sum(fit) / count(*)) + {const}), 4) + 0.0 FROM fit"),
        "augmented_objective": aug.then(f"SELECT a.src, a.dst, round(l + {RHO} / 2 * b * b + {ETA} * b, 6) + 0.0 AS objective, round(a.g + ({ETA} + {RHO} * b) * x.g, 6) + 0.0 AS g FROM gl a JOIN grad x USING (src, dst), (SELECT (SELECT sum(fit) FROM fit) + {LAM} * (SELECT sum(abs(w)) FROM probe) AS l, (SELECT sum(scale) FROM st1) AS b)"),
        "adam_one_step": step().then("SELECT src, dst, round(w - 0.01 * g / (abs(g) + 1e-8), 6) + 0.0 AS w, round(0.1 * g, 6) + 0.0 AS m1, round(0.001 * g * g, 6) + 0.0 AS m2 FROM gl"),
        "inner_three_steps": three.then(f"SELECT src, dst, {r6('w')} FROM e{N_STEPS}"),
        "inner_batched_steps": batched.then(f"SELECT src, dst, {r6('w')} FROM b{N_STEPS}"),
        "proximal_step": step(0.0).then(f"SELECT src, dst, round(sign(v) * greatest(abs(v) - 0.01 * {LAM}, 0), 6) + 0.0 AS w FROM (SELECT src, dst, w - 0.01 * g AS v FROM gl) WHERE abs(v) > 0.01 * {LAM}"),
        "threshold_theta": base.order_sequence_sql().then(f"SELECT src, dst, {r6('w')} FROM edges WHERE abs(w) >= 0.4"),
        "minibatch_draw": rat().then("SELECT sample_id, count(*)::BIGINT AS n FROM cells WHERE sample_id IN (SELECT sample_id FROM (SELECT DISTINCT sample_id FROM cells) ORDER BY md5('7:0:' || sample_id) LIMIT 20) GROUP BY 1"),
        "ratings_centred": rat().then(f"SELECT sample_id, node_id, {r6('x')} FROM cells"),
        "indicators_documents": numbered(docs_ind),
        "tokens_dictionary": r"SELECT count(*)::BIGINT AS n_nodes, sum(support)::BIGINT AS cells, max(support)::BIGINT AS top FROM (SELECT w, count(DISTINCT doc_id) AS support FROM (SELECT doc_id, unnest(string_split_regex(trim(text), '\s+')) AS w FROM documents) WHERE w <> '' GROUP BY w) WHERE support >= 5",
        "mixed_nodes": numbered(mixed),
        "embeddings_long": "SELECT i AS node_id, round(sum(embedding[i + 1]::DOUBLE), 4) + 0.0 AS total, count(*)::BIGINT AS n FROM embeddings, (SELECT range::INTEGER AS i FROM range(64)) WHERE embedding[i + 1] <> 0 GROUP BY i",
        "correlation_graph": rm().then("SELECT m.a, m.b, round(m.c / sqrt(x.c * y.c), 6) + 0.0 AS r FROM m JOIN m x ON x.a = m.a AND x.b = m.a JOIN m y ON y.a = m.b AND y.b = m.b WHERE m.a <> m.b ORDER BY abs(m.c / sqrt(x.c * y.c)) DESC, m.a, m.b LIMIT 15"),
        "refit_two_parents": probe().then(
            "SELECT 5 AS src, 6 AS dst, round(c56 / c55, 6) + 0.0 AS w, round(c66 - c56 * c56 / c55, 6) + 0.0 AS variance FROM (SELECT max(c) FILTER (a = 5 AND b = 6) AS c56, max(c) FILTER (a = 5 AND b = 5) AS c55, max(c) FILTER (a = 6 AND b = 6) AS c66 FROM moments)"
            " UNION ALL SELECT 1, 4, round(c14 / c11, 6) + 0.0, round(c44 - c14 * c14 / c11, 6) + 0.0 FROM (SELECT max(c) FILTER (a = 1 AND b = 4) AS c14, max(c) FILTER (a = 1 AND b = 1) AS c11, max(c) FILTER (a = 4 AND b = 4) AS c44 FROM moments)"
            " UNION ALL SELECT s, 1, round(CASE s WHEN 0 THEN w0 ELSE w6 END, 6) + 0.0, round(c11 - w0 * c01 - w6 * c16, 6) + 0.0 FROM (SELECT *, (c01 * c66 - c16 * c06) / (c00 * c66 - c06 * c06) AS w0, (c16 * c00 - c01 * c06) / (c00 * c66 - c06 * c06) AS w6 FROM (SELECT max(c) FILTER (a = 0 AND b = 0) AS c00, max(c) FILTER (a = 0 AND b = 1) AS c01, max(c) FILTER (a = 0 AND b = 6) AS c06, max(c) FILTER (a = 1 AND b = 6) AS c16, max(c) FILTER (a = 6 AND b = 6) AS c66, max(c) FILTER (a = 1 AND b = 1) AS c11 FROM moments)), (SELECT unnest([0, 6]) AS s)"
        ),
        "top_links": links().add("nodes_", nodes).then(f"SELECT src, x.label AS src_label, dst, y.label AS dst_label, {r6('w')} FROM (SELECT * FROM links ORDER BY w DESC, src, dst LIMIT 10) l LEFT JOIN nodes_ x ON x.node_id = src LEFT JOIN nodes_ y ON y.node_id = dst"),
        "propagate_scores": links().then("SELECT s.sample_id, s.node_id, round(s.score, 4) + 0.0 AS score FROM (SELECT sample_id, dst AS node_id, sum(x * w) AS score FROM cells JOIN links ON node_id = src GROUP BY 1, 2) s LEFT JOIN cells c ON c.sample_id = s.sample_id AND c.node_id = s.node_id WHERE c.node_id IS NULL"),
        "explain_scores": links().then("SELECT sample_id, node_id, nth::INTEGER AS nth, via, round(part, 4) + 0.0 AS part FROM (SELECT *, row_number() OVER (PARTITION BY sample_id, node_id ORDER BY abs(part) DESC, via) AS nth FROM (SELECT sample_id, dst AS node_id, src AS via, x * w AS part FROM cells JOIN links ON node_id = src)) WHERE nth <= 2"),
        "ego_graph": links().add("pos", "SELECT * FROM links WHERE w > 0").add("near_", "SELECT 11 AS n UNION SELECT dst FROM pos WHERE src = 11 UNION SELECT src FROM pos WHERE dst = 11").then(f"SELECT src, dst, {r6('w')}, sign(w)::INTEGER AS sign FROM pos WHERE src IN (SELECT n FROM near_) AND dst IN (SELECT n FROM near_)"),
        "degree_profile": links().add("pos", "SELECT * FROM links WHERE w > 0").then("SELECT p.node_id, (SELECT count(*) FROM pos WHERE dst = p.node_id)::BIGINT AS in_degree, (SELECT count(*) FROM pos WHERE src = p.node_id)::BIGINT AS out_degree, popularity FROM (SELECT node_id, count(DISTINCT sample_id)::BIGINT AS popularity FROM cells GROUP BY 1) p"),
    }
