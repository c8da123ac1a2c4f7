"""The update log: netting, applying to a graph, and making replayable streams from a graph."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from threading import Lock

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hotgraph.functions.digests import pairs_below
from hotgraph.functions.expressions import stable_key
from hotgraph.operators.ranks import FEW, numbered
from hotgraph.sources.graphs import ends
from hotgraph.storage import counted, prepare, settle

#: Keys among which one task may pick all deletions of a stream.
MOST_PICKS = 2_000_000
#: Edges whose keys one task hashes, where there are tasks enough.
TASK_PAIRS = 1 << 20


def net_changes(log: DataFrame, conflict: str = "remove_then_add") -> tuple[DataFrame, DataFrame]:
    """(added, removed) edges of a log with op e+ or e-.

    remove_then_add: removals concern edges from before the chunk, so an edge that is also added stays. last_wins: of each
    edge the operation with the largest (ts, seq) counts, whatever the order in which messages came.
    """
    log = log.where("op in ('e+', 'e-')")
    if conflict == "last_wins":
        last = log.groupBy("src", "dst").agg(F.max_by("op", F.struct("ts", "seq")).alias("op"))
        return last.where("op = 'e+'").select("src", "dst"), last.where("op = 'e-'").select("src", "dst")
    if conflict != "remove_then_add":
        raise ValueError("conflict is remove_then_add or last_wins")
    ops = log.groupBy("src", "dst").agg(F.bool_or(F.col("op") == "e+").alias("added"))
    return ops.where("added").select("src", "dst"), ops.where("not added").select("src", "dst")


def merge_updates(edges: DataFrame, added: DataFrame, removed: DataFrame) -> DataFrame:
    """Edges without the removed ones and with the added ones, as a set: present additions and absent removals do nothing."""
    kept = edges.select("src", "dst").join(removed.select("src", "dst"), ["src", "dst"], "left_anti")
    new = added.select("src", "dst").distinct().join(kept, ["src", "dst"], "left_anti")
    return kept.unionByName(new)


def apply_log(edges: DataFrame, vertices: DataFrame, log: DataFrame, conflict: str = "remove_then_add") -> tuple[DataFrame, DataFrame]:
    """(edges, vertices) after a log with any of e+, e-, v+, v-. A removed vertex takes its edges along.

    Vertices that lose all their edges stay; ends of added edges join.
    """
    added, removed = net_changes(log, conflict)
    gone = log.where("op = 'v-'").select(F.col("src").alias("id")).distinct()
    merged = merge_updates(edges, added, removed)
    merged = merged.join(gone.select(F.col("id").alias("src")), "src", "left_anti").join(
        gone.select(F.col("id").alias("dst")), "dst", "left_anti"
    )
    named = log.where("op = 'v+'").select(F.col("src").alias("id"))
    every = vertices.select("id").union(ends(added)).union(named).distinct().join(gone, "id", "left_anti")
    return merged.select("src", "dst"), every


def drop_vertices(edges: DataFrame, ids: DataFrame) -> DataFrame:
    gone = ids.select("id").distinct()
    return edges.join(gone.withColumnRenamed("id", "src"), "src", "left_anti").join(
        gone.withColumnRenamed("id", "dst"), "dst", "left_anti"
    ).select("src", "dst")


def _bound(size: int, n: int) -> int | None:
    """Bound of 32 bits under which, of n keys that are even over all hexadecimal texts, `size` or more begin but for very
    rare cases, which are counted; None where half of all would.
    """
    share = (size + 7 * size**0.5 + 100) / max(n, 1)
    return int(share * 16**8) if share < 0.5 else None


def _hashed(edges: DataFrame, n: int, salts: list[int], bounds: list[int], first: int) -> DataFrame:
    """(src, dst, batch, key) of the n rows of edges(src, dst, since) with keys under the bounds, one for each batch from
    the first on, and since before it.
    """
    prepare(edges.sparkSession)
    spark, salt = edges.sparkSession, F.element_at(F.array(*map(F.lit, salts)), F.col("batch") - first + 1).cast("string")
    most = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = min(most, max(2 * spark.sparkContext.defaultParallelism, n // TASK_PAIRS))  # more would fill no arrays
    hit = edges.repartition(parts, "src", "dst").mapInArrow(pairs_below([str(x) for x in salts], bounds, first), "src bigint, dst bigint, batch int")
    return hit.select("*", F.md5(F.concat_ws("-", "src", "dst", salt).cast("binary")).alias("key"))


def _salts(queries: int, seed: int) -> list[int]:
    return [seed * 1000 + q for q in range(1, queries + 1)]


def drawn(edges: DataFrame, size: int, queries: int, count: int, seed: int = 42) -> DataFrame | None:
    """(src, dst, batch, key): the edges whose keys are small enough to be among the `size` additions (batch 0) or the
    `count` deletions of a chunk (batches from 1), all from one pass over the edges.

    Of a chunk's keys twice as many as it deletes are meant to be there, as chunks before seldom take any of them; whoever
    picks sees whether they were enough. None where these are too many, or the bounds too large, for that to pay, or where
    fewer than `size` are under theirs. Streams over the same frame that differ by their order alone share what is found.
    """
    with edges.__dict__.setdefault("_drawing", Lock()):
        made = edges.__dict__.setdefault("_drawn", {})
        what = (size, queries, count, seed)
        if what not in made and (low := _drawn(edges, *what)) is not None:
            made[what] = low
        return made.get(what)


def _drawn(edges: DataFrame, size: int, queries: int, count: int, seed: int) -> DataFrame | None:
    n = counted(edges)
    first, later = _bound(size, n), _bound(2 * count, n - size)
    if not count or 2 * count * queries > MOST_PICKS or first is None or later is None:
        return None
    rows = edges.select("src", "dst", F.lit(-1).alias("since"))
    low = settle(_hashed(rows, n, [seed, *_salts(queries, seed)], [first] + [later] * queries, 0), "low")
    return low if low.where("batch = 0").count() >= size else None


def sample_additions(edges: DataFrame, size: int, queries: int, seed: int = 42, order: str = "shuffled", low: DataFrame | None = None) -> DataFrame:
    """(src, dst, seq, batch): the `size` edges with the smallest keys, dealt to `queries` chunks of equal size.

    order: shuffled numbers them by key, incidence by source and target. low: what drawn() has found.
    """
    key = stable_key("src", "dst", seed=seed)
    keyed = edges.select("src", "dst", key.alias("key")) if low is None else low.where("batch = 0").select("src", "dst", "key")
    by = [F.col(c) for c in (("key", "src", "dst") if order == "shuffled" else ("src", "dst"))]
    if size <= FEW:
        few = keyed.orderBy("key", "src", "dst").limit(size)
        few = few.withColumn("seq", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(*by)))  # `size` rows
    else:
        few = numbered(keyed, F.col("key"), F.col("src"), F.col("dst"), name="seq").where(F.col("seq") <= size)
        if order != "shuffled":
            few = numbered(few.drop("seq"), *by, name="seq")
    chunk = max(1, size // queries)
    return few.select("src", "dst", F.col("seq").cast("bigint").alias("seq")).withColumn(
        "batch", F.least(F.floor((F.col("seq") - 1) / chunk) + 1, F.lit(queries)).cast("int")
    )


def sample_deletions(
    initial: DataFrame, additions: DataFrame, queries: int, count: int, seed: int = 42, low: DataFrame | None = None
) -> DataFrame:
    """(src, dst, batch): for each chunk the `count` edges with the smallest salted keys among those of the initial graph
    and of earlier chunks, none twice. low: what drawn() has found.

    Where each chunk finds its deletions among the keys that drawn() has found, those are they, as it has all keys under a
    bound. As chunks before can take no more than all deletions, that many smallest keys of each chunk are always enough to
    pick from: one pass over the edges and one task over these. Where they are too many for a task, one pass a chunk.
    """
    size = count * queries
    pick = lambda rows, *by: settle(rows.coalesce(1).sortWithinPartitions("batch", *by).select("batch", "src", "dst").mapInPandas(_picker(count), "src bigint, dst bigint, batch int"), "deleted")
    if low is not None:
        since = additions.select("src", "dst", F.col("batch").alias("since"))
        low = low.where("batch > 0").join(since, ["src", "dst"], "left").where("since is null or since < batch").select("batch", "key", "src", "dst")
        if counted(gone := pick(low, "key", "src", "dst")) == size:
            return gone
    pool = settle(
        initial.select("src", "dst", F.lit(0).alias("since")).union(additions.select("src", "dst", F.col("batch").alias("since"))), "pool"
    )
    if size * queries <= MOST_PICKS:
        pair = F.concat_ws("-", F.col("src").cast("string"), F.col("dst").cast("string")).alias("pair")
        dealt = pool.select("src", "dst", pair, F.explode(F.sequence(F.col("since") + 1, F.lit(queries))).alias("batch"))  # a row a later chunk
        salt = (F.lit(seed * 1000) + F.col("batch")).cast("string")
        keyed = dealt.where(F.col("batch") <= queries).select("src", "dst", "batch", F.md5(F.concat_ws("-", "pair", salt).cast("binary")).alias("key"))
        by = Window.partitionBy("batch").orderBy("key", "src", "dst")
        n = counted(initial)
        few = _low(keyed, size, queries, n, lambda bound: _hashed(pool, n, _salts(queries, seed), [bound] * queries, 1))
        few = few.withColumn("k", F.row_number().over(by)).where(F.col("k") <= size)
        return pick(few, "k")
    taken = None
    for q in range(1, queries + 1):
        open_ = pool.where(F.col("since") < q)
        if taken is not None:
            open_ = open_.join(taken, ["src", "dst"], "left_anti")
        key = stable_key("src", "dst", seed=seed * 1000 + q)
        now = open_.select("src", "dst", key.alias("key")).orderBy("key", "src", "dst").limit(count).select("src", "dst", F.lit(q).alias("batch"))
        now = settle(now, "deleted")
        taken = now if taken is None else taken.union(now)
    return taken.select("src", "dst", "batch")


def _low(keyed: DataFrame, size: int, queries: int, n: int, pick: Callable[[int], DataFrame] | None = None) -> DataFrame:
    """Rows of keyed(batch, key, ..) with the `size` smallest keys of each batch among them; each batch has n or more rows.
    pick: a faster way to the rows whose key begins under a bound of 32 bits.

    Only keys under a bound are sorted. Where it leaves a batch too few, which is counted, all rows stay.
    """
    bound = _bound(size, n)
    if bound is None:
        return keyed
    low = _enough((keyed if pick is None else pick(bound)).where(F.col("key") < F.lit(format(bound, "08x"))), size, queries)
    return keyed if low is None else low


def _enough(low: DataFrame, size: int, queries: int) -> DataFrame | None:
    """low(batch, ..), written, if each batch has `size` rows."""
    low = settle(low, "low")
    counts = [r["count"] for r in low.groupBy("batch").count().collect()]  # a row a batch
    return low if len(counts) == queries and min(counts) >= size else None


def _picker(count: int) -> Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]]:
    """Of rows in the order of (batch, k): the first `count` edges of each batch that no batch before has taken."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        taken: set[tuple[int, int]] = set()
        left: dict[int, int] = {}
        for part in parts:
            out = []
            for batch, src, dst in zip(part["batch"], part["src"], part["dst"], strict=True):
                if left.setdefault(batch, count) and (src, dst) not in taken:
                    left[batch] -= 1
                    taken.add((src, dst))
                    out.append((src, dst, batch))
            yield pd.DataFrame(out, columns=["src", "dst", "batch"])

    return run


def make_stream(
    edges: DataFrame, size: int, queries: int = 50, deletion_ratio: float = 0.2, seed: int = 42, order: str = "shuffled"
) -> tuple[DataFrame, DataFrame]:
    """(initial edges, updates): additions leave the initial graph, and each chunk also removes a share of its size."""
    count = round(max(1, size // queries) * deletion_ratio)
    low = drawn(edges, size, queries, count, seed)
    additions = settle(sample_additions(edges, size, queries, seed, order, low), "additions")
    start = edges.select("src", "dst").join(additions.select("src", "dst"), ["src", "dst"], "left_anti")
    if low is None:
        initial = settle(start, "initial")
        gone = sample_deletions(initial, additions, queries, count, seed) if count else None
    else:  # the deletions need the first graph only where too few keys are left, and then make it as a plain frame
        with ThreadPoolExecutor(1) as other:
            writing = other.submit(settle, start, "initial")
            gone = sample_deletions(start, additions, queries, count, seed, low)
            initial = writing.result()
    ts = F.timestamp_seconds(F.lit(1_700_000_000) + F.col("batch") * 60)
    updates = additions.select("seq", ts.alias("ts"), "batch", F.lit("e+").alias("op"), "src", "dst")
    if gone is not None:
        numbered = gone.withColumn("seq", F.lit(size) + F.row_number().over(Window.partitionBy("batch").orderBy("src", "dst")))
        updates = updates.unionByName(
            numbered.select(F.col("seq").cast("bigint").alias("seq"), ts.alias("ts"), "batch", F.lit("e-").alias("op"), "src", "dst")
        )
    return initial, updates


def save_stream(updates: DataFrame, path: str) -> None:
    """One folder for each chunk, to be replayed unchanged for every parameter set."""
    updates.repartition("batch").write.partitionBy("batch").parquet(path)


def load_stream(spark, path: str) -> DataFrame:  # noqa: ANN001
    return spark.read.parquet(path)
