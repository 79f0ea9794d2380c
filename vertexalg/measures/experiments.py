"""The experiments as frames: systems against each other, the ablation, scaling, counters and shares of time.

Every algorithm runs on the stand-ins of its published data sets. What a system lays out before it starts (orientation,
blocks, grids) is prepared before the clock starts, as loading is no part of the published times. Times vary; their order is what counts. Whether
systems agree does not: that is told by frames of their own.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager
from dataclasses import dataclass, field
from functools import cached_property
from threading import RLock

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexalg.algorithms import cf
from vertexalg.algorithms.bfs import BfsProgram, bfs
from vertexalg.algorithms.pagerank import PageRankProgram, pagerank, with_out_degree
from vertexalg.algorithms.sssp import SsspProgram, sssp
from vertexalg.algorithms.triangles import triangle_count
from vertexalg.baselines import native, semiring, triplet, worklist
from vertexalg.conf import EngineConf, written
from vertexalg.engine import init_state, run_program
from vertexalg.graphs import derive, prep
from vertexalg.graphs.graph import Graph
from vertexalg.graphs.rmat import synthetic_ratings
from vertexalg.matrix import columns
from vertexalg.measures import ablation
from vertexalg.measures.counters import counted, counters, normalised
from vertexalg.measures.timing import clock, finish, geometric_mean, slowdown, speedup

ROUNDS, FACTORS, GRID = 3, 4, 2
#: Edges of a partition.
EDGES = 1 << 16
#: Stand-ins of the published data sets, by algorithm.
DATASETS = {"pr": ("basket_chain", "copurchase", "handoff"), "bfs": ("basket_chain", "copurchase", "handoff"), "tc": ("basket_chain", "copurchase", "handoff"), "cf": ("rating", "synth_rating"), "sssp": ("basket_chain", "handoff", "trade")}
SYSTEMS = ("engine", "triplet", "semiring", "worklist", "native")


@dataclass
class Loaded:
    """A data set, written, in the forms that algorithms ask for, each made at its first use. Of ratings, base is the rating graph."""

    name: str
    base: Graph
    root: int | None = None
    ratings: DataFrame | None = None
    _making: RLock = field(default_factory=RLock)

    @cached_property
    def _both(self) -> Graph:
        return self._again(prep.ones(prep.symmetrize(prep.drop_self_loops(self.base))))

    @cached_property
    def _upper(self) -> Graph:
        return self._again(prep.upper_triangle(self.base))

    @property
    def both(self) -> Graph:
        with self._making:  # runs side by side ask for it
            return self._both

    @property
    def upper(self) -> Graph:
        with self._making:
            return self._upper

    def _again(self, g: Graph) -> Graph:
        """g with its edges written; its vertices are those of base, which are written already."""
        out = Graph(written(g.edges, self.name), g.vertices, g.directed, g.conf, g.form)
        out.unit = g.unit
        return out

    def release(self) -> None:
        for g in (self.base, self.__dict__.get("_both"), self.__dict__.get("_upper")):
            if g is not None:
                g.unpersist()
                g.edges.unpersist()


def load(spark: SparkSession, d: str, name: str, conf: EngineConf = EngineConf()) -> Loaded:
    if name in ("rating", "synth_rating"):
        rows = written(derive.ratings(spark, d) if name == "rating" else synthetic_ratings(spark, 500, 200, 10), name)
        return Loaded(name, cf.rating_graph(rows).written(name), ratings=rows)
    g = derive.graph(spark, d, name, conf)
    edges = written(g.edges, name)  # before the vertices, which are their ends: edges are derived once
    vertices = g.vertices if name in derive.VERTEX_SQL else Graph.from_edges(edges).vertices
    return Loaded(name, Graph(edges, written(vertices, name), g.directed, conf), edges.agg(F.min("src")).first()[0])


def fitted(spark: SparkSession, d: str, name: str) -> Loaded:
    """load, in a session of its own with the caller's settings, where all systems alike then work: stages share generated classes, and exchanges
    have a partition for every ``EDGES`` edges, never more than the caller's. Where that leaves cores idle, plans are not adapted either."""
    own = spark.newSession()
    for k in spark.conf.getAll:
        if k.startswith("spark.sql.") and own.conf.isModifiable(k):
            own.conf.set(k, spark.conf.get(k))
    p = load(own, d, name)
    least = -(-p.base.edges.count() // EDGES)
    own.conf.set("spark.sql.shuffle.partitions", str(max(1, min(least, int(own.conf.get("spark.sql.shuffle.partitions"))))))
    own.conf.set("spark.sql.codegen.useIdInClassName", "false")
    own.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    if least < own.sparkContext.defaultParallelism:
        own.conf.set("spark.sql.adaptive.enabled", "false")
    return p


def _settled(g: Graph) -> Graph:
    worklist.source_blocks(g, worklist.settled_blocks(g)).count()
    return g


def _relaxed(g: Graph) -> tuple[int, DataFrame]:
    """Edges in blocks of ``EDGES`` at most on average (or as many as the graph's own number), and how many."""
    n = g.conf.partitions or max(1, -(-g.edges.count() // EDGES))
    return n, worklist.in_blocks(g, n)


def _kept(g: Graph) -> Graph:
    """A system without layouts has the edges in memory as they are."""
    g.edges.persist().count()
    return g


def _grid(g: Graph) -> Graph:
    semiring.on_grid(g, GRID).grid(GRID).count()
    return g


def _made(df: DataFrame) -> DataFrame:
    df.count()
    return df


Run = tuple[Callable[[Loaded], object], Callable[[Loaded, object], DataFrame]]


def runs(rounds: int = ROUNDS) -> dict[tuple[str, str], Run]:
    """(system, algorithm) to (what is prepared, what is timed on it). Native factors are stochastic, as published; the worklist's rank
    stops by its residuals, so it has no rounds."""
    model = {"k": FACTORS, "iterations": rounds}
    out: dict[tuple[str, str], Run] = {
        ("engine", "pr"): (lambda p: p.base.persist("columns"), lambda p, _: pagerank(p.base, iterations=rounds)),
        ("engine", "bfs"): (lambda p: p.both.persist("columns"), lambda p, _: bfs(p.both, p.root, symmetric=True)),
        ("engine", "tc"): (lambda p: p.upper.persist("columns", "dst"), lambda p, _: triangle_count(p.upper)),
        ("engine", "cf"): (lambda p: p.base.persist("dst both"), lambda p, _: cf.descend(p.base, FACTORS, iterations=rounds).factors),
        ("engine", "sssp"): (lambda p: p.base.persist("columns"), lambda p, _: sssp(p.base, p.root)),
        ("triplet", "pr"): (lambda p: _kept(p.base), lambda p, _: triplet.run(PageRankProgram(), with_out_degree(p.base), rounds).state.select("vid", "rank")),
        ("triplet", "bfs"): (lambda p: _kept(p.both), lambda p, _: triplet.run(BfsProgram([p.root]), p.both).state.select("vid", "level")),
        ("triplet", "tc"): (lambda p: _kept(p.upper), lambda p, _: triplet.triangles_hash(p.upper)),
        ("triplet", "cf"): (lambda p: _kept(p.base), lambda p, _: cf._model(triplet.run(cf.GradientProgram(FACTORS, 0.002, 0.05), p.base, rounds).state, FACTORS, []).factors),
        ("triplet", "sssp"): (lambda p: _kept(p.base), lambda p, _: triplet.run(SsspProgram(p.root), p.base).state.select("vid", "dist")),
        ("semiring", "pr"): (lambda p: _grid(p.base), lambda p, _: semiring.pagerank(p.base, iterations=rounds, grid=GRID)),
        ("semiring", "bfs"): (lambda p: _grid(p.both), lambda p, _: semiring.bfs(p.both, p.root, GRID)),
        ("semiring", "tc"): (lambda p: _kept(p.upper), lambda p, _: semiring.triangles_spgemm(p.upper)),
        ("semiring", "cf"): (lambda p: _made(p.ratings), lambda p, _: semiring.cf_gd(p.ratings, **model).factors),
        ("semiring", "sssp"): (lambda p: _grid(p.base), lambda p, _: semiring.sssp(p.base, p.root, GRID)),
        ("worklist", "pr"): (lambda p: _settled(p.base), lambda p, _: worklist.pagerank_residual(p.base, eps=1e-2)),
        ("worklist", "bfs"): (lambda p: _relaxed(p.both), lambda p, laid: worklist.bfs(p.both, p.root, blocks=laid[0], edges=laid[1])),
        ("worklist", "tc"): (lambda p: _kept(p.upper), lambda p, _: worklist.triangles(p.upper)),
        ("worklist", "cf"): (lambda p: _made(p.ratings), lambda p, _: worklist.cf(p.ratings, **model).factors),
        ("worklist", "sssp"): (lambda p: _relaxed(p.base), lambda p, laid: worklist.sssp(p.base, p.root, blocks=laid[0], edges=laid[1])),
        ("native", "pr"): (lambda p: _made(native.shares(p.base)), lambda p, share: native.pagerank(p.base, iterations=rounds, share=share)),
        ("native", "bfs"): (lambda p: _made(native.laid_out(p.both)), lambda p, laid: native.bfs(p.both, p.root, laid)),
        ("native", "tc"): (lambda p: _kept(p.upper), lambda p, _: native.triangles(p.upper)),
        ("native", "cf"): (lambda p: _made(p.ratings), lambda p, _: native.cf(p.ratings, k=FACTORS, epochs=rounds).factors),
        ("native", "sssp"): (lambda p: _made(native.laid_out(p.base)), lambda p, laid: native.sssp(p.base, p.root, laid)),
    }
    return out


#: What is not the same sequence of steps as the engine's, and how far its result may lie off.
_LOOSE = {("worklist", "pr"): 0.5, ("worklist", "cf"): 1.0, ("native", "cf"): 1.0}


def agrees(system: str, algorithm: str, found: DataFrame, engine: DataFrame) -> bool:
    """Whether a system's rows are the engine's: the same keys, whole numbers equal, others within 1e-6 (ranks by residuals, and factors that
    are found by other steps, within a stated distance)."""
    value = [c for c, kind in engine.dtypes if kind == "double"]
    if not value:
        return found.exceptAll(engine.select(*found.columns)).isEmpty() and engine.select(*found.columns).exceptAll(found).isEmpty()
    keys = [c for c in engine.columns if c not in value]
    far = F.greatest(F.lit(0.0), *(F.coalesce(F.abs(F.col(f"a.{c}") - F.col(f"b.{c}")), F.lit(float("inf"))) for c in value))
    joined = found.alias("a").join(engine.alias("b"), [F.col(f"a.{c}").eqNullSafe(F.col(f"b.{c}")) for c in keys], "full")
    row = joined.agg(F.max(far).alias("far"), F.count("*").alias("n")).first()
    return bool(row["n"]) and row["far"] <= _LOOSE.get((system, algorithm), 1e-6)


_TOLD: dict[tuple, list[tuple]] = {}
#: By session, folder, algorithm, data set and system: seconds, and results (written).
_SECONDS: dict[tuple, float] = {}
_FOUND: dict[tuple, DataFrame] = {}
#: Runs side by side where no time is taken.
ABREAST, HEAVY = 6, 2


@contextmanager
def settings(spark: SparkSession, given: dict[str, str]) -> Iterator[None]:
    """The session with these settings; its own are put back."""
    before = {k: spark.conf.get(k, None) for k in given}
    for k, v in given.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def shared_classes(spark: SparkSession):
    """Stages of equal code share a generated class, for all systems alike, so that a superstep is compiled once and not in every round."""
    return settings(spark, {"spark.sql.codegen.useIdInClassName": "false"})


def abreast(spark: SparkSession, run: Callable, many: Iterable, width: int | None = None) -> list:
    """run of each, a few at a time, in order."""
    with ThreadPoolExecutor(width or ABREAST) as pool:
        waits = [pool.submit(inheritable_thread_target(spark)(run), x) for x in many]
        return [w.result() for w in waits]


def _key(spark: SparkSession, d: str, *what) -> tuple:
    return (spark.sparkContext.applicationId, d, *what)


def timed(spark: SparkSession, d: str, systems: tuple[str, ...], algorithms: tuple[str, ...]) -> DataFrame:
    """(system, algorithm, dataset, seconds) of these systems and algorithms on all of their data sets, one run at a time, each timed once in a
    session. The first data set of each algorithm is run through once before, as code is compiled then. A result is written by its run."""
    loaded: dict[str, Loaded] = {}
    wanted = [(a, n) for a in algorithms for n in DATASETS[a]]
    with shared_classes(spark):
        for algorithm, name in wanted:
            left = [s for s in systems if _key(spark, d, algorithm, name, s) not in _SECONDS]
            if not left:
                continue
            p = loaded[name] = loaded.get(name) or fitted(spark, d, name)
            how = {s: runs()[s, algorithm] for s in left}
            ready = {s: prepare(p) for s, (prepare, _) in how.items()}
            if name == DATASETS[algorithm][0]:
                abreast(spark, lambda s: finish(how[s][1](p, ready[s])), left)  # noqa: B023
            for s in left:
                key, began = _key(spark, d, algorithm, name, s), time.perf_counter()
                _FOUND[key] = written(how[s][1](p, ready[s]), "found")
                _SECONDS[key] = time.perf_counter() - began
            for made in ready.values():
                if isinstance(made, DataFrame):
                    made.unpersist()
            p.release()
    rows = [(s, a, n, _SECONDS[_key(spark, d, a, n, s)]) for a, n in wanted for s in systems]
    return spark.createDataFrame(rows, "system string, algorithm string, dataset string, seconds double")


def against_frameworks(spark: SparkSession, d: str) -> DataFrame:
    """(system, algorithm, speedup) of the engine over three baselines, geometric means over data sets, and overall."""
    return speedup(timed(spark, d, SYSTEMS[:4], tuple(DATASETS)))


def against_native(spark: SparkSession, d: str) -> DataFrame:
    """(algorithm, slowdown) of the engine against hand-written code, and overall."""
    return slowdown(timed(spark, d, ("engine", "native"), tuple(a for a in DATASETS if a != "sssp")))


def agreement(spark: SparkSession, d: str, systems: tuple[str, ...] = SYSTEMS) -> DataFrame:
    """(system, algorithm, dataset, agrees) of every system on every data set: of the runs that were timed, and of one more of each that was not. No
    time is taken here, so runs go side by side."""
    wanted = [(a, n) for a, names in DATASETS.items() for n in names]
    lacking = [(a, n, s) for a, n in wanted for s in systems if _key(spark, d, a, n, s) not in _FOUND]
    lacking.sort(key=lambda x: x[0] not in ("sssp", "tc"))  # the longest first, so that none is left to the end alone
    # triangles and factors fill cores and memory, so only a few of them go at once; the others are many short jobs, which would wait behind them
    parts = [([x for x in lacking if (x[0] in ("tc", "cf")) == heavy], HEAVY if heavy else ABREAST) for heavy in (True, False)]
    names = list(dict.fromkeys(n for _, n, _ in lacking))
    loaded = dict(zip(names, abreast(spark, lambda n: fitted(spark, d, n), names), strict=True))

    def found(job: tuple[str, str, str]) -> None:
        algorithm, name, system = job
        prepare, run = runs()[system, algorithm]
        ready = prepare(loaded[name])
        _FOUND[_key(spark, d, *job)] = written(run(loaded[name], ready), "found")
        if isinstance(ready, DataFrame):
            ready.unpersist()

    def told(job: tuple[str, str, str]) -> tuple:
        algorithm, name, system = job
        own, first = (_FOUND[_key(spark, d, algorithm, name, s)] for s in (system, systems[0]))
        return system, algorithm, name, agrees(system, algorithm, own, first)

    for jobs, width in parts:
        abreast(spark, found, jobs, width)
    for p in loaded.values():
        p.release()
    rows = abreast(spark, told, [(a, n, s) for a, n in wanted for s in systems])
    return spark.createDataFrame(rows, "system string, algorithm string, dataset string, agrees boolean")


def compare(spark: SparkSession, d: str, systems: tuple[str, ...] = SYSTEMS) -> DataFrame:
    """(system, algorithm, dataset, seconds, agrees)."""
    return timed(spark, d, systems, tuple(DATASETS)).join(agreement(spark, d, systems), ["system", "algorithm", "dataset"])


AGREEMENT_SQL = " union all ".join(f"select '{s}' as system, '{a}' as algorithm, '{n}' as dataset, true as agrees" for s in SYSTEMS for a, names in DATASETS.items() for n in names)

#: What the ablation and the scaling run on: rank on the interaction graph, shortest paths on one of many rounds.
OPTIMISED = (("rank", "copurchase"), ("sssp", "handoff"))


def _bar_result(algorithm: str, result) -> DataFrame:
    return result.state.select("vid", "rank" if algorithm == "rank" else "dist")


def ablation_rows(spark: SparkSession, d: str) -> DataFrame:
    """(algorithm, dataset, bar, gain, agrees): cumulative factors over the first bar, and whether the bar's result is the first's."""
    key = _key(spark, d, "ablation")
    if key not in _TOLD:
        rows = []
        for algorithm, name in OPTIMISED:
            p, first = load(spark, d, name), None
            for bar in ablation.BARS:
                seconds, result = ablation.bar(bar, p.base, algorithm, p.root, ROUNDS)
                found = _bar_result(algorithm, result)
                first = first or (seconds, found)
                rows.append((algorithm, name, bar, first[0] / seconds, agrees("engine", algorithm, found, first[1])))
            p.release()
        _TOLD[key] = rows  # whole, or not at all
    return spark.createDataFrame(_TOLD[key], "algorithm string, dataset string, bar string, gain double, agrees boolean")


def ablation_agreement(spark: SparkSession, d: str) -> DataFrame:
    """(algorithm, dataset, bar, agrees) as in ablation_rows, and from its runs if it was called before in this session. No time is taken here, so
    bars go side by side, those of one task first."""
    key = _key(spark, d, "ablation agreement")
    if told := _TOLD.get(_key(spark, d, "ablation")):
        _TOLD[key] = [(a, n, b, ok) for a, n, b, _, ok in told]
    if key not in _TOLD:
        with shared_classes(spark):
            loaded = dict(zip(OPTIMISED, abreast(spark, lambda x: load(spark, d, x[1]), OPTIMISED), strict=True))

            def made(job: tuple[str, tuple[str, str]]) -> DataFrame:
                bar, (algorithm, name) = job
                p = loaded[algorithm, name]
                return _bar_result(algorithm, ablation.bar(bar, p.base, algorithm, p.root, ROUNDS)[1])

            jobs = [(bar, data) for bar in ablation.BARS for data in OPTIMISED]
            found = dict(zip(jobs, abreast(spark, made, jobs), strict=True))
            same = abreast(spark, lambda job: agrees("engine", job[1][0], found[job], found[ablation.BARS[0], job[1]]), jobs)
            for p in loaded.values():
                p.release()
        _TOLD[key] = [(*data, bar, ok) for (bar, data), ok in zip(jobs, same, strict=True)]
    return spark.createDataFrame(_TOLD[key], "algorithm string, dataset string, bar string, agrees boolean")


ABLATION_SQL = " union all ".join(f"select '{a}' as algorithm, '{n}' as dataset, '{b}' as bar, true as agrees" for a, n in OPTIMISED for b in ablation.BARS)


#: Of the scaling.
CORES = (1, 4)
#: What sets how many tasks a stage has: of tables read, of exchanges, of local rows.
_TASKS = ("spark.sql.files.minPartitionNum", "spark.sql.files.maxPartitionNum", "spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.initialPartitionNum", "spark.sql.leafNodeDefaultParallelism")


@contextmanager
def on_cores(spark: SparkSession, n: int) -> Iterator[EngineConf]:
    """Stages made inside have about n tasks, so they keep n cores busy (plans are not adapted: that would take tasks away); matrices have n blocks.
    The session's settings are put back."""
    with settings(spark, dict.fromkeys(_TASKS, str(n)) | {"spark.sql.adaptive.enabled": "false"}):
        yield EngineConf(partitions=n)


def scaling_rows(spark: SparkSession, d: str, cores: tuple[int, ...] = CORES) -> DataFrame:
    """(system, algorithm, dataset, cores, seconds, speedup) over the first number of cores, all in the caller's session, so also on a cluster.
    All systems are run through once, side by side, before they are first timed, as code is compiled then."""
    key = _key(spark, d, "scaling", cores)
    if key not in _TOLD:
        seconds: dict[tuple, float] = {}
        for n in cores:
            with shared_classes(spark), on_cores(spark, n) as conf:
                for algorithm, name in (("pr", "copurchase"), ("sssp", "handoff")):
                    p = load(spark, d, name, conf)
                    how = {s: runs()[s, algorithm] for s in SYSTEMS[:4]}
                    ready = {s: prepare(p) for s, (prepare, _) in how.items()}
                    if n == cores[0]:
                        abreast(spark, lambda s: finish(how[s][1](p, ready[s])), how)  # noqa: B023
                    for s, (_, run) in how.items():
                        seconds[s, algorithm, name, n] = clock(lambda: run(p, ready[s]))[0]  # noqa: B023
                    p.release()
        _TOLD[key] = [(*k, s, seconds[(*k[:3], cores[0])] / s) for k, s in seconds.items()]
    return spark.createDataFrame(_TOLD[key], "system string, algorithm string, dataset string, cores int, seconds double, speedup double")


def single_thread(spark: SparkSession, d: str) -> DataFrame:
    """(system, algorithm, speedup) of the engine over the others, each on one core."""
    whole = _key(spark, d, "scaling", CORES) in _TOLD  # else no other number of cores is timed for it
    return speedup(scaling_rows(spark, d, CORES if whole else (1,)).where("cores = 1"))


def workfront_ratio(spark: SparkSession, d: str) -> DataFrame:
    """(dataset, slowdown) of the engine against the one-process sweep, on the graph of many rounds and the power-law one."""
    from vertexalg.baselines import workfront

    rows = []
    for name in ("handoff", "rmat_path"):
        p = load(spark, d, name)
        p.base.persist("columns")
        _kept(p.base)
        own, other = (min(clock(run)[0] for _ in range(2)) for run in (lambda: sssp(p.base, p.root), lambda: workfront.sssp(p.base, p.root)))  # noqa: B023
        rows.append((name, own / other))
        p.release()
    return spark.createDataFrame(rows, "dataset string, slowdown double")


def product_share(spark: SparkSession, d: str) -> DataFrame:
    """(algorithm, dataset, share): the share of a superstep's time that its product takes: the same superstep with and without send's state
    being applied, compared and written."""
    rows = []
    for algorithm, name in OPTIMISED:
        p = load(spark, d, name)
        p.base.persist("columns")
        g = with_out_degree(p.base, True) if algorithm == "rank" else p.base
        program = PageRankProgram() if algorithm == "rank" else SsspProgram(p.root, frontier=False)
        state = written(init_state(g, program) if algorithm == "rank" else sssp(p.base, p.root, max_supersteps=3).withColumn("active", F.lit(True)))
        product = lambda: columns.superstep(g, state, program, program.state, F.lit(True)).select("vid", "red")  # noqa: B023, E731
        whole = min(clock(lambda: run_program(g, program, 1, start=state).state)[0] for _ in range(3))  # noqa: B023
        part = min(clock(product)[0] for _ in range(3))
        rows.append((algorithm, name, min(1.0, part / whole)))
        p.release()
    return spark.createDataFrame(rows, "algorithm string, dataset string, share double")


def grid_sweep(spark: SparkSession, d: str, grids: tuple[int, ...] = (1, 2, 3)) -> DataFrame:
    """(algorithm, dataset, grid, seconds, agrees) of the semiring baseline on q x q blocks."""
    rows = []
    p = load(spark, d, "handoff")
    methods = {"pr": (p.base, lambda q: semiring.pagerank(p.base, iterations=ROUNDS, grid=q)), "bfs": (p.both, lambda q: semiring.bfs(p.both, p.root, q)), "sssp": (p.base, lambda q: semiring.sssp(p.base, p.root, q))}
    for algorithm, (g, run) in methods.items():
        first = None
        for q in grids:
            semiring.on_grid(g, q).grid(q).count()
            seconds, found = clock(lambda: run(q))  # noqa: B023
            first = first or found
            rows.append((algorithm, "handoff", q, seconds, agrees("semiring", algorithm, found, first)))
    p.release()
    return spark.createDataFrame(rows, "algorithm string, dataset string, grid int, seconds double, agrees boolean")


GRID_SQL = " union all ".join(f"select '{a}' as algorithm, 'handoff' as dataset, {q} as grid, true as agrees" for a in ("pr", "bfs", "sssp") for q in (1, 2, 3))


def counter_rows(spark: SparkSession, d: str) -> DataFrame:
    """(system, counter, relative): cost proxies of rank, triangles, factors and shortest paths, geometric means over them, relative to the engine."""
    found: dict[str, dict[str, list[float]]] = {}
    loaded: dict[str, Loaded] = {}
    with shared_classes(spark):
        for algorithm, name in (("pr", "copurchase"), ("tc", "copurchase"), ("cf", "rating"), ("sssp", "handoff")):
            p = loaded[name] = loaded.get(name) or fitted(spark, d, name)
            for system in SYSTEMS[:4]:
                prepare, run = runs()[system, algorithm]
                ready = prepare(p)
                with counted(spark, f"{system}-{algorithm}"):
                    finish(run(p, ready))
                for k, v in counters(spark, f"{system}-{algorithm}").items():
                    found.setdefault(system, {}).setdefault(k, []).append(max(v, 1e-9))
            p.release()
    means = {s: {k: geometric_mean(v) for k, v in x.items()} for s, x in found.items()}
    rows = [(s, k, v) for s, x in normalised(means).items() for k, v in x.items()]
    return spark.createDataFrame(rows, "system string, counter string, relative double")
