"""The serving session: updates are registered as they come, and each query is answered by the strategy chosen for it."""

from __future__ import annotations

import time
from collections.abc import Iterable
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hotgraph.operators.iterate import LOCAL_LINKS, rank_exact
from hotgraph.operators.selection import select_hot
from hotgraph.operators.stats import both_degrees
from hotgraph.operators.summary import Summary, incoming, rank_approximate, split
from hotgraph.operators.updates import apply_log, net_changes
from hotgraph.plans import policies
from hotgraph.plans.cost import pays
from hotgraph.schema import UPDATES, Params, require
from hotgraph.sources.graphs import ends
from hotgraph.storage import discard, settle

#: Share of the edges that may have changed before the base table is written anew.
COMPACT = 0.1
#: Single messages held before they are registered together.
HELD = 10_000

RUN_LOG = (
    "graph string, params struct<r: double, n: int, delta: double>, query int, strategy string, n_vertices bigint, "
    "n_edges bigint, n_hot bigint, inner_edges bigint, boundary_edges bigint, phases map<string, double>, "
    "rbo double, rbo_full double"
)


class PhaseTimer:
    """Seconds of wall clock by phase: ingest, construct, compute."""

    def __init__(self) -> None:
        self.phases: dict[str, float] = {}

    @contextmanager
    def phase(self, name: str):  # noqa: ANN201
        began = time.perf_counter()
        try:
            yield
        finally:
            self.phases[name] = self.phases.get(name, 0.0) + time.perf_counter() - began


class Hooks:
    """The five steps a user may replace. All get the session."""

    def __init__(self, policy: policies.Policy = policies.always(policies.APPROXIMATE)) -> None:
        self.policy = policy

    def setup(self, session: QuerySession) -> None:
        """Before the first answer is computed."""

    def should_apply(self, session: QuerySession, pending: policies.Pending) -> bool:
        """Whether pending updates enter the graph at this query."""
        return pending.adds + pending.removes > 0

    def choose(self, session: QuerySession, pending: policies.Pending) -> str:
        return self.policy(pending)

    def after_answer(self, session: QuerySession, row: dict) -> None:
        """With the statistics of the answer."""

    def teardown(self, session: QuerySession) -> None:
        """When the session stops."""


class QuerySession:
    """Graph, pending updates and last answer, all written tables.

    The edges are a base and the state of all edges that changed since it was written, so a chunk of updates costs a
    scan of the base and a small table; the base is written anew once a share `compact` has changed. Counts and degrees
    follow from the net changes. snapshot: last_computed compares degrees with the last point that was computed;
    every_query with the last query, so that changes before a reused answer are forgotten. guard: recompute where the
    summary would not pay. kernel and local_links: where loops and hot sets run (see power_loop). keep: answers and
    their tables stay after the next query; without, only the last two are there. distinct: edges are a written set already.
    """

    def __init__(
        self, edges: DataFrame, params: Params = Params(), hooks: Hooks | None = None, *, vertices: DataFrame | None = None, name: str = "",
        kernel: str = "auto", conflict: str = "remove_then_add", snapshot: str = "last_computed", guard: bool = False,
        local_links: int | None = None, compact: float = COMPACT, keep: bool = True, distinct: bool = False,
    ) -> None:
        if snapshot not in ("last_computed", "every_query"):
            raise ValueError("snapshot is last_computed or every_query")
        self.spark, self.params, self.hooks = edges.sparkSession, params, hooks or Hooks()
        self.name, self.kernel, self.conflict, self.snapshot, self.guard = name, kernel, conflict, snapshot, guard
        self.local_links, self.compact, self.keep = LOCAL_LINKS if local_links is None else local_links, compact, keep
        self.held = edges.select("src", "dst") if distinct else settle(edges.select("src", "dst").distinct(), "edges")
        self.delta: DataFrame | None = None
        self.named = vertices
        self.log: list[DataFrame] = []
        self.buffer: list[tuple] = []
        self.touched: DataFrame | None = None
        self.adds = self.removes = self.ends = self.vertex_ops = self.n_query = self.version = 0
        self.rows: list[dict] = []
        self.summary: Summary | None = None
        self.hot: DataFrame | None = None
        self._spent: list[DataFrame | None] = []

    @property
    def edges(self) -> DataFrame:
        """(src, dst) of the graph as it is now."""
        if self.delta is None:
            return self.held
        return self.held.join(self.delta.select("src", "dst"), ["src", "dst"], "left_anti").unionByName(self.delta.where("there").select("src", "dst"))

    @property
    def vertices(self) -> DataFrame:
        return self.degrees.select("id")

    def start(self, scores: DataFrame | None = None) -> QuerySession:
        """The first exact answer, or one that is known already."""
        self.hooks.setup(self)
        p = self.params
        v = ends(self.held)
        self.degrees = self._counted(v if self.named is None else v.union(self.named.select("id")).distinct())
        self.n_edges, self.n_vertices = self.held.count(), self.degrees.count()
        found = scores if scores is not None else self._exact()
        self.scores = settle(found.select("id", "score"), "scores")
        self.earlier_scores = None
        self.base = self.degrees
        return self

    def _counted(self, vertices: DataFrame) -> DataFrame:
        """(id, out_deg, in_deg) of the vertices."""
        zero = lambda c: F.coalesce(c, F.lit(0).cast("bigint")).alias(c)
        return settle(vertices.join(both_degrees(self.edges), "id", "left").select("id", zero("out_deg"), zero("in_deg")), "degrees")

    def _degree(self) -> Column:
        """The kind of degree whose change makes a seed."""
        return {"out": F.col("out_deg"), "in": F.col("in_deg"), "total": F.col("out_deg") + F.col("in_deg")}[self.params.degree]

    def _exact(self) -> DataFrame:
        p = self.params
        return rank_exact(self.edges, p.beta, p.iterations, vertices=self.vertices, kernel=self.kernel, local_links=self.local_links)

    # messages -----------------------------------------------------------------------------------------------------

    def add(self, src: int, dst: int) -> None:
        self._message("e+", src, dst)

    def remove(self, src: int, dst: int) -> None:
        self._message("e-", src, dst)

    def _message(self, op: str, src: int, dst: int | None) -> None:
        """Single messages are held and registered together: before the next query, or when there are HELD of them."""
        self.buffer.append((len(self.buffer), None, self.n_query + 1, op, src, dst))
        if len(self.buffer) >= HELD:
            self._flush()

    def _flush(self) -> None:
        if self.buffer:
            rows, self.buffer = self.buffer, []
            self.enqueue(self.spark.createDataFrame(rows, UPDATES))

    def enqueue(self, updates: DataFrame) -> None:
        """Register updates without touching the graph; their counts are known from now on."""
        self._flush()
        held = settle(require(updates, UPDATES).where("op <> 'query'"), "log")
        ids = held.select("op", F.posexplode(F.array("src", "dst")).alias("at", "id"))
        counts = ids.agg(
            F.count_if((F.col("at") == 0) & F.col("op").isin("e+", "v+")).alias("a"), F.count_if((F.col("at") == 0) & F.col("op").isin("e-", "v-")).alias("r"),
            F.count_distinct("id").alias("t"), F.count_if((F.col("at") == 0) & F.col("op").isin("v+", "v-")).alias("v"),
        ).first()
        self.adds, self.removes, self.ends = self.adds + counts.a, self.removes + counts.r, self.ends + counts.t
        self.vertex_ops += counts.v
        self.log.append(held)

    def pending(self, tier: str = "balanced") -> policies.Pending:
        """Changes since the last computed answer. touched adds up the vertices of each registered part of the log."""
        self._flush()
        return policies.Pending(self.n_query, self.adds, self.removes, self.ends, self.n_vertices, self.n_edges, tier)

    def statistics(self) -> dict[str, int]:
        """Totals of the pending log, available before it is applied."""
        self._flush()
        out = {"adds": self.adds, "removes": self.removes, "touched": 0, "new_vertices": 0}
        if self.log:
            ids = self._log().select(F.explode(F.array("src", "dst")).alias("id")).where("id is not null").distinct()
            out["touched"] = ids.count()
            out["new_vertices"] = ids.join(self.vertices, "id", "left_anti").count()
        return out

    def _log(self) -> DataFrame:
        every = self.log[0]
        for x in self.log[1:]:
            every = every.unionByName(x)
        return every

    # queries ------------------------------------------------------------------------------------------------------

    def query(self, tier: str = "balanced") -> DataFrame:
        """(id, score): the answer, which is also kept as the next version."""
        self.n_query += 1
        timer, pending, before = PhaseTimer(), self.pending(tier), self.base
        if self.hooks.should_apply(self, pending) and self.log:
            with timer.phase("ingest"):
                self._apply()
        strategy = self.hooks.choose(self, pending)
        counts = {"n_hot": 0, "inner_edges": 0, "boundary_edges": 0}
        if strategy == policies.APPROXIMATE:
            with timer.phase("construct"):
                counts = self._summarise(before)
            if self.guard and not pays(
                self.n_edges, self.n_vertices, counts["inner_edges"], counts["boundary_edges"], self.params.iterations, self.params.n
            ):
                strategy = policies.RECOMPUTE
        with timer.phase("compute"):
            self._compute(strategy, counts)
        if strategy != policies.REUSE or self.snapshot == "every_query":
            self.base, self.touched = self.degrees, None
        if strategy != policies.REUSE and not self.log:
            self.adds = self.removes = self.ends = 0
        self._clean()
        row = {
            "graph": self.name, "params": (self.params.r, self.params.n, self.params.delta), "query": self.n_query, "strategy": strategy,
            "n_vertices": self.n_vertices, "n_edges": self.n_edges, **counts, "phases": dict(timer.phases), "rbo": None, "rbo_full": None,
        }
        self.rows.append(row)
        self.hooks.after_answer(self, row)
        return self.scores

    def _clean(self) -> None:
        """Delete tables that nothing reads any more."""
        used = {getattr(x, "_settled", None) for x in (self.degrees, self.base, self.held, self.delta, self.scores, self.earlier_scores)}
        discard(*(x for x in self._spent if getattr(x, "_settled", None) not in used))
        self._spent = [x for x in self._spent if getattr(x, "_settled", None) in used]

    def _apply(self) -> None:
        log = self._log()
        old = (self.degrees, self.base, self.held, self.delta, self.touched, *self.log)
        if not self.vertex_ops:
            self._net(log)
        else:
            edges, vertices = apply_log(self.edges, self.vertices, log, self.conflict)
            vertices = settle(vertices, "vertices")
            self.held, self.delta = settle(edges, "edges"), None
            self.degrees = self._counted(vertices)
            self.n_edges = self.held.count()
            old = (*old, vertices)
        if self.params.mean_degree == "touched":
            ids = log.select(F.explode(F.array("src", "dst")).alias("id")).where("id is not null")
            self.touched = settle((ids if self.touched is None else ids.union(self.touched)).distinct(), "touched")
        self.log, self.vertex_ops, self.version = [], 0, self.version + 1
        self.n_vertices = self.degrees.count()
        self._spent += old

    def _net(self, log: DataFrame) -> None:
        """Edge changes: what is really new or gone, by one scan of the edges; degrees and counts from these alone."""
        key = ["src", "dst"]
        added, removed = net_changes(log, self.conflict)
        asked = settle(added.withColumn("there", F.lit(True)).unionByName(removed.withColumn("there", F.lit(False))), "asked")
        present = self.edges.join(asked.select(*key), key, "left_semi").withColumn("was", F.lit(True))
        real = settle(asked.join(present, key, "left").where(F.col("there") != F.coalesce("was", F.lit(False))).select(*key, "there"), "changes")
        n = real.agg(F.count_if("there").alias("new"), F.count_if(~F.col("there")).alias("gone")).first()
        self.n_edges += n.new - n.gone
        sign = F.when(F.col("there"), 1).otherwise(-1).cast("bigint")
        end = lambda c, out, into: F.struct(F.col(c).alias("id"), (sign * out).alias("o"), (sign * into).alias("i"))
        moved = real.select(F.explode(F.array(end("src", 1, 0), end("dst", 0, 1))).alias("e")).select("e.*").groupBy("id").agg(F.sum("o").alias("o"), F.sum("i").alias("i"))
        plus = lambda c, x: (F.coalesce(c, F.lit(0)) + F.coalesce(x, F.lit(0))).cast("bigint").alias(c)
        self.degrees = settle(self.degrees.join(moved, "id", "full_outer").select("id", plus("out_deg", "o"), plus("in_deg", "i")), "degrees")
        if self.delta is None:
            self.delta = real
        else:
            self.delta = settle(self.delta.join(real.select(*key), key, "left_anti").unionByName(real), "delta")
        self._spent += [asked, real]
        if self.delta.count() > self.compact * self.n_edges:
            self._spent.append(self.delta)
            self.held, self.delta = settle(self.edges, "edges"), None

    def _summarise(self, before: DataFrame) -> dict[str, int]:
        now = self.degrees.select("id", self._degree().alias("deg_now"))
        change = now.join(before.select("id", self._degree().alias("deg_prev")), "id", "left").select("id", "deg_prev", "deg_now")
        self.hot = settle(
            select_hot(
                self.edges, self.edges, self.scores, self.params, previous_scores=self.earlier_scores, touched=self.touched, change=change,
                facts=self.degrees, kernel="local" if self.kernel == "local" or self.kernel == "auto" and max(self.n_edges, self.n_vertices) <= self.local_links else "distributed",
            ), "hot",
        )
        known = self.degrees.where("out_deg > 0").select("id", "out_deg")
        aimed = settle(incoming(self.edges, self.hot, self.scores, known), "aimed")
        self.summary = split(aimed, self.hot)
        self._spent += [] if self.keep else [aimed, self.hot]
        n = aimed.agg(F.count_if("inner").alias("inner"), F.count_if(~F.col("inner")).alias("cold")).first()
        return {"n_hot": self.hot.count(), "inner_edges": n["inner"], "boundary_edges": n["cold"]}

    def _compute(self, strategy: str, counts: dict[str, int]) -> None:
        p, found = self.params, None
        if strategy == policies.RECOMPUTE:
            found = self._exact()
        elif strategy == policies.APPROXIMATE and counts["n_hot"]:
            found = rank_approximate(
                self.summary, self.scores, self.vertices, beta=p.beta, iterations=p.iterations, warm=p.warm, kernel=self.kernel,
                local_links=self.local_links,
            )
        elif strategy not in (policies.APPROXIMATE, policies.REUSE):
            raise ValueError(f"no strategy {strategy}")
        if found is not None:
            self._spent += [] if self.keep else [self.earlier_scores]
            self.earlier_scores, self.scores = self.scores, settle(found.select("id", "score"), "scores")

    def run(self, messages: Iterable[tuple]) -> list[DataFrame]:
        """Answers to the queries among messages ("add", src, dst), ("remove", src, dst), ("query",)."""
        out = []
        for kind, *ends_ in messages:
            if kind == "query":
                out.append(self.query(*ends_))
            else:
                {"add": self.add, "remove": self.remove}[kind](*ends_)
        return out

    def run_log(self) -> DataFrame:
        names = ("graph", "params", "query", "strategy", "n_vertices", "n_edges", "n_hot", "inner_edges", "boundary_edges", "phases", "rbo", "rbo_full")
        return self.spark.createDataFrame([tuple(r[n] for n in names) for r in self.rows], RUN_LOG)

    def stop(self) -> None:
        self.hooks.teardown(self)
