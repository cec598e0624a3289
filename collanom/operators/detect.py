"""Detection as a distributed plan: wide rows in chunks with a halo, array scores, islands, small programmes.

A window of penalised saving zero or less never improves the optimum, so only positive candidates leave
the scoring kernel. Candidates that overlap form islands; islands don't share time, so the optimum is
the sum of their optima and every island is solved by itself, streaming its candidates by their ends.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..config import DetectorConfig
from ..functions.costs import FAMILIES
from .blocks import Chain, Kernel, dense_optimum, greedy_chain, pruned_optimum, undominated

#: Cells (rows times components) of a chunk, where that makes between two and ten halos.
CHUNK_CELLS = 1 << 18
#: Series up to which their sizes are fetched and broadcast: five numbers each.
BROADCAST_SERIES = 100_000
_CANDIDATES = "series_id string, s bigint, e bigint, k int, score double, kind string"


@dataclass
class DetectionResult:
    """`chosen` has windows and points; the other frames are views of it, all lazy."""

    chosen: DataFrame
    candidates: DataFrame
    long: DataFrame
    cfg: DetectorConfig
    rates: DataFrame | None = None

    def release(self) -> None:
        """Frees the kept candidates once the results have been read."""
        self.candidates.unpersist()

    @property
    def windows(self) -> DataFrame:
        return self.chosen.where("kind = 'window'").select("series_id", "s", "e", "k", "score")

    @property
    def points(self) -> DataFrame:
        return self.chosen.where("kind = 'point'").select("series_id", F.col("e").alias("t"), "k", "score")

    @property
    def affected(self) -> DataFrame:
        return affected_components(self.long, self.windows, self.cfg, self.rates)

    @property
    def point_components(self) -> DataFrame:
        return point_components(self.long, self.points, self.cfg, self.rates)

    @property
    def objective(self) -> DataFrame:
        return self.chosen.groupBy("series_id").agg(F.sum("score").alias("objective"), F.count("*").alias("n_found"))


def series_sizes(long: DataFrame) -> DataFrame:
    """(series_id, n, p, first, last): times, components, and the first and last time."""
    sizes = long.groupBy("series_id").agg(F.min("t").alias("first"), F.max("t").alias("last"), F.max("component").alias("p"))
    return sizes.select("series_id", (F.col("last") - F.col("first") + 1).alias("n"), "p", "first", "last")


@dataclass(frozen=True)
class Sizes:
    """The sizes of all series, as a frame for joins, and the greatest of them."""

    frame: DataFrame
    n: int
    p: int
    series: int


def known_sizes(long: DataFrame) -> Sizes:
    """The sizes: fetched and broadcast if there are at most `BROADCAST_SERIES` series, else left to a join by key."""
    sizes = series_sizes(long)
    rows = sizes.limit(BROADCAST_SERIES + 1).collect()
    if len(rows) > BROADCAST_SERIES:
        most = sizes.agg(F.max("n").alias("n"), F.max("p").alias("p"), F.count("*").alias("series")).first()
        return Sizes(sizes, int(most["n"]), int(most["p"]), int(most["series"]))
    frame = F.broadcast(long.sparkSession.createDataFrame([tuple(r) for r in rows], "series_id string, n bigint, p int, first bigint, last bigint"))
    return Sizes(frame, max((int(r["n"]) for r in rows), default=0), max((int(r["p"]) for r in rows), default=0), len(rows))


def chunk_rows(cfg: DetectorConfig, p: int = 1) -> int:
    """Rows of a chunk: ten halos, down to two where there are many components."""
    return max(2 * cfg.m, min(10 * cfg.m, CHUNK_CELLS // max(p, 1)))


def with_halo(long: DataFrame, sizes: Sizes, cfg: DetectorConfig, size: int, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, n, p, first, last, chunk, t, xs): each time's vector in its own chunk and, near a chunk's end, in the next too.

    Chunks count from the first time of the series. `rates` (series_id, component, mu) travel along as an array.
    """
    if size < cfg.m:
        raise ValueError("a chunk must hold the longest window")
    place = F.col("t") - F.col("first")
    own = F.floor(place / size).cast("long")
    twice = F.when(place >= (own + 1) * size - cfg.m, F.array(own, own + 1)).otherwise(F.array(own))
    head = ("series_id", "n", "p", "first", "last")
    cells = long.join(sizes.frame, "series_id").select(*head, "t", "component", "x", F.explode(twice).alias("chunk")).where(F.col("chunk") * size < F.col("n"))
    # dealt by (series, chunk) once: the rows of a time and the chunk's kernel then need no further shuffle
    dealt = cells.repartition(_tasks(long, sizes, size), "series_id", "chunk")
    rows = dealt.groupBy(*head, "chunk", "t").agg(_in_order("x").alias("xs"))
    if rates is not None:
        rows = rows.join(rates.groupBy("series_id").agg(_in_order("mu").alias("rates")), "series_id")
    return rows


def _tasks(long: DataFrame, sizes: Sizes, size: int) -> int:
    """Tasks for the chunks: a number that Spark doesn't change, as it would join small chunks whose scoring takes long."""
    chunks = sizes.series * -(-sizes.n // size)
    cells = sizes.series * sizes.n * sizes.p
    return max(1, min(chunks, max(4 * long.sparkSession.sparkContext.defaultParallelism, cells // CHUNK_CELLS)))


def _in_order(value: str) -> Column:
    """The values of a time or series as an array in component order."""
    return F.transform(F.array_sort(F.collect_list(F.struct("component", value))), lambda c: c[value])


@lru_cache(maxsize=64)
def kernel_for(cfg: DetectorConfig, n: int, p: int) -> Kernel:
    """The kernel of a series' size; shared by all series of a worker, so it is never changed."""
    return Kernel(cfg.l, cfg.m, tuple(cfg.curve(n, p)), cfg.cost, cfg.w, cfg.gamma, cfg.point_price(n, p), cfg.points, widest=cfg.widest)


@dataclass(frozen=True)
class Block:
    """A chunk in a worker: its rows `x` with the halo before place `first`; `base` is the time before the first row."""

    series: str
    n: int
    p: int
    x: np.ndarray
    first: int
    base: int
    rates: np.ndarray | None

    def kernel(self, cfg: DetectorConfig) -> Kernel:
        own = kernel_for(cfg, self.n, self.p)
        if self.rates is None:
            if cfg.cost == "poisson":
                raise ValueError("the count cost needs the typical rates of the components")
            return own
        return replace(own, rates=self.rates)


def read_block(key: tuple, group: pa.Table, cfg: DetectorConfig, size: int) -> Block:
    """The rows of a chunk in order; raises on gaps, repeated times and missing values, at the chunk's edges too."""
    series, chunk = key[0].as_py(), key[1].as_py()
    n, p, start, last = (group.column(c)[0].as_py() for c in ("n", "p", "first", "last"))
    group = group.combine_chunks()
    t, xs = group.column("t").to_numpy(), group.column("xs").combine_chunks()
    xs = xs if isinstance(xs, pa.ListArray) else pa.concat_arrays(xs.chunks)
    low, high = start + max(0, chunk * size - cfg.m), min(last, start + (chunk + 1) * size - 1)
    if len(t) != high - low + 1 or pc.min(pc.list_value_length(xs)).as_py() != p or pc.max(pc.list_value_length(xs)).as_py() != p:
        raise ValueError(f"series {series} has gaps, repeated times or times without all components; fill its grid first")
    order = np.argsort(t, kind="stable")
    t, x = t[order], xs.flatten().to_numpy(zero_copy_only=False).reshape(len(t), p)[order]
    if t[0] != low or t[-1] != high or np.isnan(x).any():
        raise ValueError(f"series {series} has gaps or missing values; fill its grid first")
    rates = np.array(group.column("rates")[0].as_py(), float) if "rates" in group.column_names else None
    if rates is not None and len(rates) != p:
        raise ValueError(f"series {series} has {p} components and {len(rates)} rates")
    return Block(series, n, p, x, int(start + chunk * size - t[0]), int(t[0] - 1), rates)


def scored(block: Block, cfg: DetectorConfig, floor: float = 0.0, few: bool = False) -> dict[str, np.ndarray]:
    """The chunk's candidates as arrays s, e, k, score and is_point; `few` leaves out those that hold a better one."""
    return scored_at(block, cfg, [cfg.scale], floor, few)[0]


def scored_at(block: Block, cfg: DetectorConfig, scales: Sequence[float], floor: float = 0.0, few: bool = False) -> list[dict[str, np.ndarray]]:
    """The same at several scales of the prices: the savings, which don't depend on them, are made once."""
    kernels = [block.kernel(cfg.with_(scale=c)) for c in scales]
    saved = kernels[0].scores_of(kernels, block.x, block.first, floor)
    return [_with_points(block, cfg, kernel, found, floor, few) for kernel, found in zip(kernels, saved, strict=True)]


def _with_points(block: Block, cfg: DetectorConfig, kernel: Kernel, found: dict[str, np.ndarray], floor: float, few: bool) -> dict[str, np.ndarray]:
    s, e, k, score = (found[c] for c in ("s", "e", "k", "score"))
    is_point = np.zeros(len(s), bool)
    if kernel.points:
        over = kernel.point_matrix(block.x[block.first :]) - kernel.beta_point
        saved = np.maximum(over, 0.0).sum(axis=1)
        at = np.flatnonzero(saved > floor)
        s, e = np.concatenate([s, at + block.first]), np.concatenate([e, at + block.first + 1])
        k, score = np.concatenate([k, (over[at] > 0).sum(axis=1)]), np.concatenate([score, saved[at]])
        is_point = np.concatenate([is_point, np.ones(len(at), bool)])
    keep = undominated(s, e, score, 1e-12 if cfg.widest else 0.0) if few else slice(None)
    return {"s": s[keep].astype(np.int64) + block.base, "e": e[keep].astype(np.int64) + block.base, "k": k[keep].astype(np.int32), "score": score[keep], "is_point": is_point[keep]}


def _kinds(is_point: np.ndarray) -> pa.Array:
    return pa.array(np.where(is_point, "point", "window").tolist(), pa.string())


def candidates(long: DataFrame, cfg: DetectorConfig, floor: float = 0.0, chunk: int | None = None, rates: DataFrame | None = None, few: bool = False, sizes: Sizes | None = None) -> DataFrame:
    """All windows and points of positive penalised saving, as (series_id, s, e, k, score, kind).

    `rates`: (series_id, component, mu) for the count cost. `few` leaves out candidates that hold another one
    of a greater score in the same chunk: they are in no optimum and in no greedy selection.
    """
    sizes = sizes or known_sizes(long)
    size = chunk or chunk_rows(cfg, sizes.p)

    def score(key, group):
        block = read_block(key, group, cfg, size)
        f = scored(block, cfg, floor, few)
        return pa.table({"series_id": pa.array([block.series] * len(f["s"]), pa.string()), "s": f["s"], "e": f["e"], "k": f["k"], "score": f["score"], "kind": _kinds(f["is_point"])})

    return with_halo(long, sizes, cfg, size, rates).groupBy("series_id", "chunk").applyInArrow(score, _CANDIDATES)


def islands(found: DataFrame, min_gap: int = 0, by: tuple[str, ...] = ("series_id",), longest: int = 4096) -> DataFrame:
    """Candidates with `island`, the start of the first of them: a new one begins where a start is not below every earlier end.

    Time is cut into buckets of at least the longest candidate, so what came before reaches into the next
    bucket only: rows are ordered within buckets, and only one row a bucket is ordered over the series.
    """
    size = max(longest, 4096)
    keys = [*by, "bucket"]
    rows = found.withColumn("bucket", F.floor(F.col("s") / size)).repartition(*keys)
    order = Window.partitionBy(*keys).orderBy("s", "e", "kind")
    reached = rows.groupBy(*keys).agg(F.max("e").alias("reached")).withColumn("bucket", F.col("bucket") + 1)
    seen = F.greatest(F.max("e").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.col("reached"))
    marked = rows.join(reached, keys, "left").withColumn("seen", seen).withColumn("begins", F.when(F.col("seen").isNull() | (F.col("s") >= F.col("seen") + min_gap), F.col("s")))
    last = Window.partitionBy(*by).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    carried = marked.groupBy(*keys).agg(F.max("begins").alias("own")).select(*keys, F.last("own", ignorenulls=True).over(last).alias("carried"))
    own = F.max("begins").over(order.rowsBetween(Window.unboundedPreceding, 0))
    joined = marked.join(carried, keys).withColumn("island", F.coalesce(own, F.col("carried")))
    return joined.select(*found.columns, "island")


def solve(found: DataFrame, min_gap: int = 0, greedy: bool = False, by: tuple[str, ...] = ("series_id",), longest: int = 4096, widest: bool = False) -> DataFrame:
    """The chosen candidates: the best chain of every island (or the greedy one); of equal chains that with later starts, or with `widest` with earlier ones.

    Islands are streamed: rows come ordered by their ends, and one row per end is kept, so an island that
    covers a whole series needs memory for its length and not for its candidates. `found` is read by
    several branches; keep or write it first.
    """
    keys, names = [*by, "island"], found.columns
    marked = islands(found, min_gap, by, longest)
    if greedy:

        def chain(pdf):
            spans = list(zip(pdf["s"].tolist(), pdf["e"].tolist(), pdf["score"].tolist(), pdf["kind"].tolist(), strict=True))
            return pdf.iloc[greedy_chain(spans, min_gap)].drop(columns="island")

        return marked.groupBy(*keys).applyInPandas(chain, found.schema)
    place = F.when(F.col("kind") == "point", 0).otherwise(1)
    rows = marked.withColumn("__place", place).repartition(*keys).sortWithinPartitions(*keys, "e", "__place", F.desc("s")).select(*names, "island")
    at = {c: i for i, c in enumerate(names)}
    s_, e_, score_, kind_ = (at[c] for c in ("s", "e", "score", "kind"))
    own = [at[c] for c in by] + [len(names)]
    out = _arrow_schema(found)

    def run(batches):
        now, state = None, Chain(min_gap, widest)
        for batch in batches:
            done = []
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                island = tuple(row[i] for i in own)
                if island != now:
                    done += state.picked()
                    now, state = island, Chain(min_gap, widest)
                state.offer(row[s_], row[e_], row[score_], row[kind_], row)
            if done:
                yield _as_batch(done, out)
        if state.ends:
            yield _as_batch(state.picked(), out)

    return rows.mapInArrow(run, found.schema)


def _arrow_schema(df: DataFrame) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema

    return to_arrow_schema(df.schema)


def _as_batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [()] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(columns[i], f.type) for i, f in enumerate(schema)], schema=schema)


def detect(long: DataFrame, cfg: DetectorConfig, plan: str = "auto", rates: DataFrame | None = None) -> DetectionResult:
    """Anomalous windows and points of standardised series; counts come as they are, with their `rates`.

    `plan`: islands, greedy, tiles (islands from partial sums over tiles of components), reference or
    pruned (one task per series), or auto, which leaves it to the planner.
    """
    from ..plans.planner import choose

    sizes = known_sizes(long)
    if plan == "auto":
        plan = choose(cfg, sizes.n, sizes.p, sizes.series).programme
    if plan in ("reference", "pruned"):
        chosen = per_series(long, cfg, plan, rates=rates, sizes=sizes)
        return DetectionResult(chosen, chosen, long, cfg, rates)
    if plan == "tiles":
        from .tiles import tiled_candidates

        found = tiled_candidates(long, cfg, sizes=sizes, rates=rates).persist()
    elif plan in ("islands", "greedy"):
        found = candidates(long, cfg, rates=rates, few=True, sizes=sizes).persist()
    else:
        raise ValueError(f"unknown plan {plan}")
    return DetectionResult(solve(found, cfg.min_gap, plan == "greedy", longest=cfg.m, widest=cfg.widest), found, long, cfg, rates)


#: A chunk that holds any series whole.
_WHOLE = 1 << 40


def per_series(long: DataFrame, cfg: DetectorConfig, plan: str = "pruned", cap: int | None = None, rates: DataFrame | None = None, sizes: Sizes | None = None) -> DataFrame:
    """The whole recursion in one task per series: `reference` (every window up to m) or `pruned` (no cap on lengths unless given)."""

    def run(key, group):
        block = read_block(key, group, cfg, _WHOLE)
        kernel = replace(block.kernel(cfg), m=cfg.m if plan == "reference" else (cap or block.n))
        parts = (dense_optimum if plan == "reference" else pruned_optimum)(block.x, kernel)[1]
        sums, over = kernel.sums(block.x), kernel.point_matrix(block.x) > kernel.beta_point
        k = [int(over[s].sum()) if kind == "point" else kernel.affected(block.x, sums, s, e) for s, e, _, kind in parts]
        columns = ([p[i] for p in parts] for i in range(4))
        s, e, score, kind = columns
        return pa.table({"series_id": pa.array([block.series] * len(parts), pa.string()), "s": pa.array([v + block.base for v in s], pa.int64()), "e": pa.array([v + block.base for v in e], pa.int64()), "k": pa.array(k, pa.int32()), "score": pa.array(map(float, score), pa.float64()), "kind": pa.array(kind, pa.string())})

    return with_halo(long, sizes or known_sizes(long), cfg, _WHOLE, rates).groupBy("series_id", "chunk").applyInArrow(run, _CANDIDATES)


def pruning_profile(long: DataFrame, cfg: DetectorConfig, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, step, alive, possible): starts evaluated at each step against those without pruning."""

    def run(key, group):
        block = read_block(key, group, cfg, _WHOLE)
        profile = pruned_optimum(block.x, replace(block.kernel(cfg), m=block.n))[2]
        return pa.table({"series_id": pa.array([block.series] * block.n, pa.string()), "step": pa.array([a for a, _ in profile], pa.int64()), "alive": pa.array([b for _, b in profile], pa.int64()), "possible": pa.array([max(0, a - cfg.l + 1) for a, _ in profile], pa.int64())})

    return with_halo(long, known_sizes(long), cfg, _WHOLE, rates).groupBy("series_id", "chunk").applyInArrow(run, "series_id string, step bigint, alive bigint, possible bigint")


def rows_in_windows(long: DataFrame, windows: DataFrame, bucket: int = 128) -> DataFrame:
    """Long rows with the window (s, e] they lie in: a range join by time buckets, so that it hashes instead of looping."""
    spread = windows.select("series_id", "s", "e", *[c for c in windows.columns if c not in ("series_id", "s", "e")]).withColumn("bucket", F.explode(F.sequence(F.floor((F.col("s") + 1) / bucket), F.floor(F.col("e") / bucket))))
    return long.withColumn("bucket", F.floor(F.col("t") / bucket)).join(spread, ["series_id", "bucket"]).where((F.col("t") > F.col("s")) & (F.col("t") <= F.col("e"))).drop("bucket")


def _with_rates(rows: DataFrame, rates: DataFrame | None) -> DataFrame:
    """The rows with `rate`, the typical rate of their component (null without rates)."""
    if rates is None:
        return rows.withColumn("rate", F.lit(None).cast("double"))
    return rows.join(rates.select("series_id", "component", F.col("mu").alias("rate")), ["series_id", "component"])


def affected_components(long: DataFrame, windows: DataFrame, cfg: DetectorConfig, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, s, e, component, saving, estimate, start_lag, end_lag) of the k most improved components of each window.

    The estimate is the mean over the component's own part of the window; ties go to the lower number.
    """
    from .relational import saving_column

    rows = rows_in_windows(long, windows)
    least, w, gamma, family = max(cfg.l, FAMILIES[cfg.cost].least), cfg.w, cfg.gamma, cfg.cost
    order = Window.partitionBy("series_id", "s", "e").orderBy(F.desc("saving"), "component")
    if not w:
        per = rows.groupBy("series_id", "s", "e", "k", "component").agg(F.sum("x").alias("total"), F.sum(F.col("x") * F.col("x")).alias("squares"))
        per = _with_rates(per, rates)
        scored = per.select("series_id", "s", "e", "k", "component", saving_column(family, F.col("rate")).alias("saving"), (F.col("total") / (F.col("e") - F.col("s"))).alias("estimate"), F.lit(0).alias("start_lag"), F.lit(0).alias("end_lag"))
    else:

        def best(pdf):
            pdf = pdf.sort_values("t")
            x, rate = pdf["x"].to_numpy(float), pdf["rate"].iloc[0]
            n, p1, p2 = len(x), np.concatenate([[0], np.cumsum(x)]), np.concatenate([[0], np.cumsum(x * x)])
            top = None
            for d in range(min(w, n - 1) + 1):
                for f in range(min(w, n - 1 - d) + 1):
                    size = n - d - f
                    if size < least:
                        continue
                    total, squares = p1[n - f] - p1[d], p2[n - f] - p2[d]
                    value = float(FAMILIES[family].saving(total, squares, size, rate)) - (gamma if d or f else 0.0)
                    if top is None or value > top[0] + 1e-12:
                        top = (value, total / size, d, f)
            head = pdf.iloc[0]
            return pd.DataFrame([{"series_id": head["series_id"], "s": head["s"], "e": head["e"], "k": head["k"], "component": head["component"], "saving": top[0], "estimate": top[1], "start_lag": top[2], "end_lag": top[3]}])

        scored = _with_rates(rows, rates).groupBy("series_id", "s", "e", "component").applyInPandas(best, "series_id string, s bigint, e bigint, k int, component int, saving double, estimate double, start_lag int, end_lag int")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= F.col("k")).drop("rank", "k")


def point_components(long: DataFrame, points: DataFrame, cfg: DetectorConfig, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, t, component, z) of the components that make a time a point anomaly."""
    price: dict[tuple, float] = {}
    joined = _with_rates(long.join(points.select("series_id", "t"), ["series_id", "t"]).join(series_sizes(long), "series_id"), rates)

    def keep(batches):
        for batch in batches:
            pdf = batch.to_pandas()
            limit = np.array([price.setdefault((n, p), cfg.point_price(n, p)) for n, p in zip(pdf["n"], pdf["p"], strict=True)])
            over = FAMILIES[cfg.cost].point(pdf["x"].to_numpy(float), limit, pdf["rate"].to_numpy(float)) > limit
            yield pa.RecordBatch.from_pandas(pdf[over][["series_id", "t", "component", "x"]].rename(columns={"x": "z"}), preserve_index=False)

    return joined.select("series_id", "t", "component", "x", "n", "p", "rate").mapInArrow(keep, "series_id string, t bigint, component int, z double")


def single_window_test(long: DataFrame, cfg: DetectorConfig, floor: float = 0.0, rates: DataFrame | None = None) -> DataFrame:
    """(series_id, detected, s, e, k, score): the best window of each series; a maximum by hash aggregate, not a sort."""
    found = candidates(long, cfg.with_(points=False), floor, rates=rates)
    best = found.groupBy("series_id").agg(F.max(F.struct("score", "s", "e", "k")).alias("b"))
    return long.select("series_id").distinct().join(best, "series_id", "left").select("series_id", F.coalesce(F.col("b.score") > 0, F.lit(False)).alias("detected"), "b.s", "b.e", "b.k", "b.score")


def top_windows(long: DataFrame, cfg: DetectorConfig, n: int = 5) -> DataFrame:
    """The n best windows of each series."""
    order = Window.partitionBy("series_id").orderBy(F.desc("score"), F.desc("s"), "e")
    return candidates(long, cfg.with_(points=False)).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n)


def point_only(long: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Point anomalies without windows, with plain aggregates: (series_id, t, k, score)."""
    sizes = series_sizes(long)
    psi = F.lit(2.0) * F.log("n") if cfg.psi is None else F.lit(float(cfg.psi))
    beta = F.lit(float(cfg.beta_point)) if cfg.beta_point is not None else 2 * F.log(F.greatest(F.col("p"), F.lit(1)).cast("double")) + 2 * psi
    over = F.greatest(F.col("x") * F.col("x") - beta * cfg.scale, F.lit(0.0))
    return long.join(sizes, "series_id").groupBy("series_id", "t").agg(F.sum(F.when(over > 0, 1).otherwise(0)).cast("int").alias("k"), F.sum(over).alias("score")).where("score > 0")
