"""Choosing seeds from coverage: full scans, a lazy queue over blocks, refreshed bounds.

A memo and a collection of reverse-reachable sets have one interface: rows
(id, key, size) say that vertex `id` gains `size` as long as `key` is not
covered. All variants choose the same seeds: the largest exact gain, then the
smaller id.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadmax.operators.gains import Memo, marginal_gains
from spreadmax.session import release, rewritten, written

BLOCK = 1024
#: A commit that covers this share of all (vertex, simulation) pairs makes every stale bound useless.
REFRESH_SHARE = 0.05
#: (key, size) pairs that the driver holds at most, 16 bytes each; vertices beyond it are read again when they are visited.
HELD_PAIRS = 8_000_000


@dataclass
class Selection:
    seeds: list[tuple[int, int]] = field(default_factory=list)  # (id, gain_sum)
    visits: int = 0
    scans: int = 0

    def frame(self, spark: SparkSession) -> DataFrame:
        rows, sigma = [], 0
        for k, (v, gain) in enumerate(self.seeds):
            sigma += gain
            rows.append((k + 1, v, gain, sigma))
        return spark.createDataFrame(rows, "rank int, id long, gain_sum long, sigma_sum long")


def _ids(spark: SparkSession, ids: list[int]) -> DataFrame:
    return spark.createDataFrame(pa.table({"id": pa.array(ids, pa.int64())}))  # a local table, without a job


class MemoCoverage:
    """The memo: a key is a component of a simulation; a simulation without a row of the vertex adds 1."""

    def __init__(self, memo: Memo):
        self.memo, self.single = memo, memo.runs
        top = memo.rows.agg(F.max(F.abs("label")).alias("m")).head()["m"] or 0
        exact = top < (1 << 62) // max(1, memo.runs)
        key = F.col("label") * memo.runs + F.col("sim") if exact else F.xxhash64("sim", "label")
        self.rows = memo.rows.select("id", key.alias("key"), "size")

    def gains(self, seeds: list[int]) -> DataFrame:
        if not seeds:
            return self.memo.gains().select("id", "gain_sum")
        own = _ids(self.rows.sparkSession, seeds)
        covered = self.memo.rows.join(F.broadcast(own), "id", "left_semi").select("sim", "label").distinct()
        return marginal_gains(self.memo.vertices, self.memo.rows, covered, own, self.memo.runs)

    def much(self) -> float:
        """A gain beyond which new bounds are worth a scan."""
        return REFRESH_SHARE * self.memo.vertices.count() * self.memo.runs


class SetCoverage:
    """Sets (set_id, id): a key is a set, worth 1; vertices in no open set gain nothing and are not chosen."""

    single = 0

    def __init__(self, sets: DataFrame, set_id: str = "rr_id"):
        self.rows = sets.select("id", F.col(set_id).alias("key"), F.lit(1).cast("long").alias("size"))

    def gains(self, seeds: list[int]) -> DataFrame:
        rows = self.rows
        if seeds:
            hit = rows.join(F.broadcast(_ids(rows.sparkSession, seeds)), "id", "left_semi").select("key").distinct()
            rows = rows.join(hit, "key", "left_anti")
        return rows.groupBy("id").agg(F.sum("size").alias("gain_sum"))

    def much(self) -> float:
        return float("inf")


Coverage = MemoCoverage | SetCoverage


def select_scan(memo: Memo, k: int) -> Selection:
    """Exact gains of all vertices before every choice: k anti joins and aggregates."""
    out, source = Selection(), MemoCoverage(memo)
    while len(out.seeds) < k:
        best = source.gains([v for v, _ in out.seeds]).orderBy(F.desc("gain_sum"), "id").limit(1).collect()
        out.scans += 1
        if not best:
            break
        out.seeds.append((best[0]["id"], best[0]["gain_sum"]))
    return out


class _Bounds:
    """A table (id, gain_sum) in the order of (gain, id), fetched block by block."""

    def __init__(self, gains: DataFrame, size: int):
        self.gains, self.size = gains, size
        self.after: tuple[float, int] | None = None  # the last one fetched
        self.ended = False

    def fetch(self) -> list[tuple[int, float]]:
        rest = self.gains
        if self.after is not None:
            g, v = self.after
            rest = rest.filter((F.col("gain_sum") < g) | ((F.col("gain_sum") == g) & (F.col("id") > v)))
        rows = [(r["id"], r["gain_sum"]) for r in rest.orderBy(F.desc("gain_sum"), "id").limit(self.size).collect()]
        self.ended = len(rows) < self.size
        if rows:
            self.after = (rows[-1][1], rows[-1][0])
        return rows

    def beats(self, gain: float, v: int) -> bool:
        """Whether a vertex that is not fetched may have a larger gain, or the same and a smaller id."""
        return not self.ended and (self.after is None or gain < self.after[0] or (gain == self.after[0] and v > self.after[1]))


class _Pairs:
    """(keys, sizes) of vertices, read in blocks and held within a bound."""

    def __init__(self, rows: DataFrame, most: int):
        self.rows, self.most, self.held = rows, most, 0
        self.of: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def load(self, ids: list[int]) -> None:
        if self.held > self.most:
            self.of, self.held = {}, 0
        new = [v for v in ids if v not in self.of]
        if not new:
            return
        none = np.zeros(0, np.int64)
        self.of |= {v: (none, none) for v in new}
        got = self.rows.join(F.broadcast(_ids(self.rows.sparkSession, new)), "id").toArrow()  # rows of one block
        ids_, keys, sizes = (got.column(c).to_numpy() for c in ("id", "key", "size"))
        order = np.argsort(ids_, kind="stable")
        ids_, keys, sizes = ids_[order], keys[order], sizes[order]
        starts = np.flatnonzero(np.concatenate(([True], ids_[1:] != ids_[:-1]))) if len(ids_) else np.zeros(0, int)
        for a, b in zip(starts, np.append(starts[1:], len(ids_)), strict=False):
            self.of[int(ids_[a])] = (keys[a:b].copy(), sizes[a:b].copy())
        self.held += len(ids_)


def _within(keys: np.ndarray, taken: np.ndarray) -> np.ndarray:
    """Which keys are in `taken`, which is sorted."""
    if not len(taken):
        return np.zeros(len(keys), bool)
    return taken[np.minimum(np.searchsorted(taken, keys), len(taken) - 1)] == keys


def _rest_of_round(source: Coverage, table: DataFrame, newer: dict[int, int], seeds: list[int]) -> tuple[int, int, int, DataFrame] | None:
    """What a queue does until its next choice, in one scan: (the vertex chosen, its gain, how many are visited, the bounds after it).

    A queue visits the vertices whose bounds come before the gain of the one that it then chooses. `newer` holds bounds
    that the driver knows better than `table` does.
    """
    spark = table.sparkSession
    known = F.broadcast(spark.createDataFrame(list(newer.items()), "id long, newer long"))  # at most a block for each seed
    bounds = table.join(F.broadcast(_ids(spark, seeds)), "id", "left_anti").join(known, "id", "left")
    bounds = bounds.select("id", F.coalesce("newer", "gain_sum").alias("bound"))
    fresh = source.gains(seeds).select("id", F.col("gain_sum").alias("fresh"))
    both = written(bounds.join(fresh, "id", "left").select("id", "bound", F.coalesce("fresh", F.lit(0)).alias("fresh")), "bounds")
    top = both.orderBy(F.desc("fresh"), "id").limit(1).collect()
    if not top:
        release(both)
        return None
    v, gain = top[0]["id"], top[0]["fresh"]
    visited = (F.col("bound") > gain) | ((F.col("bound") == gain) & (F.col("id") <= v))
    visits = both.filter(visited).count()
    after = both.filter(F.col("id") != v).select("id", F.when(visited, F.col("fresh")).otherwise(F.col("bound")).alias("gain_sum"))
    return v, gain, visits, rewritten(both, after, "gains")


def select(source: Coverage, k: int, block: int = BLOCK, lookahead: bool = False, refresh: bool = False, held: int = HELD_PAIRS) -> Selection:
    """A lazy queue: stale gains are upper bounds, so a vertex whose fresh gain stays on top is chosen.

    Only blocks of the queue leave the cluster; a further block is fetched before a
    choice that an unfetched vertex could still beat. `lookahead` also keeps the
    gain given the best vertex of the round, which saves a visit when that one is
    chosen. `refresh` recomputes all gains in one scan after a choice that covers
    much, and begins the queue anew from exact bounds. Without `lookahead`, a round
    of more than `block` visits ends on the cluster (`_rest_of_round`); seeds and
    visits are those of the queue.
    """
    out, covered = Selection(), np.zeros(0, np.int64)
    chosen: set[int] = set()
    much = source.much() if refresh else 0.0
    table = written(source.gains([]), "gains")
    top, pairs = _Bounds(table, block), _Pairs(source.rows, held)
    heap: list[tuple[int, int, int]] = []  # (-gain, id, seeds at that time)
    ahead: dict[int, tuple[int, int, int]] = {}  # id -> (best of the round, seeds then, gain given it too)
    newer: dict[int, int] = {}  # bounds that are newer than those of the table: at most `block` visits a round

    def push(stamp: int) -> None:
        for v, g in top.fetch():
            if v not in chosen:
                heapq.heappush(heap, (-g, v, stamp))

    def keys_of(v: int) -> tuple[np.ndarray, np.ndarray]:
        if v not in pairs.of:  # with those that are likely to be visited next
            pairs.load([v, *[x for _, x, _ in heapq.nsmallest(block, heap)]])
        return pairs.of[v]

    def gain(v: int, besides: int | None = None) -> int:
        keys, sizes = keys_of(v)
        gone = _within(keys, covered)
        if besides is not None:
            gone = gone | _within(keys, np.sort(keys_of(besides)[0]))
        return (source.single - len(keys) if source.single else 0) + int(sizes[~gone].sum())

    push(0)
    stamp0, tried = 0, 0
    best: tuple[int, int] | None = None  # best fresh vertex of this round
    while len(out.seeds) < k:
        if not heap:
            if top.ended:
                break
            push(stamp0)
            continue
        g, v, stamp = -heap[0][0], heap[0][1], heap[0][2]
        if top.beats(g, v):
            push(stamp0)
            continue
        if g <= 0 and not source.single:
            break
        heapq.heappop(heap)
        if stamp == len(out.seeds):
            covered = np.union1d(covered, keys_of(v)[0])
            out.seeds.append((v, int(g)))
            chosen.add(v)
            best, tried = None, 0
            if not (refresh and g > much and len(out.seeds) < k):
                continue
        elif tried >= block and not lookahead:
            found = _rest_of_round(source, table, newer, [x for x, _ in out.seeds])
            if found is None or (found[1] <= 0 and not source.single):
                break
            v, fresh, visits, after = found
            out.visits += visits - (best is not None and v == best[0])  # the best one so far was visited before
            out.seeds.append((v, fresh))
            chosen.add(v)
            covered = np.union1d(covered, keys_of(v)[0])
            release(table)
            table, newer = after, {}
            top, heap, stamp0, best, tried = _Bounds(table, block), [], len(out.seeds) - 1, None, 0
            if not (refresh and fresh > much and len(out.seeds) < k):
                continue
        elif not (refresh and tried >= block):  # else a look-ahead queue renews its bounds: one scan is cheaper than further visits
            seen = ahead.get(v)
            if lookahead and seen is not None and seen[1] == len(out.seeds) - 1 and out.seeds[-1][0] == seen[0]:
                fresh = seen[2]
            else:
                fresh = gain(v)
                out.visits += 1
                tried += 1
            if lookahead and best is not None:
                ahead[v] = (best[0], len(out.seeds), gain(v, best[0]))
            if best is None or (fresh, -v) > (best[1], -best[0]):
                best = (v, fresh)
            heapq.heappush(heap, (-fresh, v, len(out.seeds)))
            newer[v] = fresh
            continue
        out.scans += 1
        table = rewritten(table, source.gains([x for x, _ in out.seeds]), "gains")
        top, pairs = _Bounds(table, block), _Pairs(source.rows, held)
        heap, stamp0, ahead, best, tried, newer = [], len(out.seeds), {}, None, 0, {}
        push(stamp0)
    release(table)
    return out


def select_lazy(memo: Memo, k: int, block: int = BLOCK, lookahead: bool = False, refresh: bool = False, held: int = HELD_PAIRS) -> Selection:
    return select(MemoCoverage(memo), k, block, lookahead, refresh, held)


def select_refresh(memo: Memo, k: int, block: int = BLOCK) -> Selection:
    return select_lazy(memo, k, block, refresh=True)


def lazy_greedy(
    first: dict[int, float] | DataFrame, evaluate: Callable[[list[int], list[int]], dict[int, float]], k: int, ahead: int = 8,
    beside: Callable | None = None, block: int = BLOCK,
) -> tuple[list[tuple[int, float]], int]:
    """The queue of the simulated baselines: `evaluate(seeds, candidates)` gives fresh gains.

    `first`: the bounds to begin with, of which a table (id, gain_sum) is fetched in
    blocks as far as the queue needs it. The top `ahead` stale vertices are
    evaluated together. `beside(seeds, candidates, best)` makes it a look-ahead
    queue: it also gives the gains that follow if `best`, the best vertex of the
    round so far, is chosen; where it is, those vertices are fresh without a further visit.
    """
    table = None if isinstance(first, dict) else _Bounds(first, block)
    heap = [(-g, v, 0) for v, g in first.items()] if table is None else []
    heapq.heapify(heap)
    seeds: list[tuple[int, float]] = []
    visits = 0
    best: tuple[float, int] | None = None  # (-gain, id)
    known: dict[int, tuple[tuple[int, ...], float]] = {}  # id -> (seeds, gain given them)

    def filled() -> bool:
        """Whether there is a top, once every bound that may beat it is fetched."""
        while table is not None and not table.ended and (not heap or table.beats(-heap[0][0], heap[0][1])):
            for v, g in table.fetch():
                heapq.heappush(heap, (-g, v, 0))
        return bool(heap)

    while len(seeds) < k and filled():
        if heap[0][2] == len(seeds):
            g, v, _ = heapq.heappop(heap)
            seeds.append((v, -g))
            best = None
            continue
        stale = []
        while len(stale) < ahead and filled() and heap[0][2] != len(seeds):
            stale.append(heapq.heappop(heap)[1])
        chosen = [v for v, _ in seeds]
        fresh = {v: known[v][1] for v in stale if v in known and known[v][0] == tuple(chosen)}
        visit = [v for v in stale if v not in fresh]
        visits += len(visit)
        if visit and beside is not None and best is not None:
            gains, later = beside(chosen, visit, best[1])
            fresh |= gains
            known |= {v: ((*chosen, best[1]), g) for v, g in later.items()}
        elif visit:
            fresh |= evaluate(chosen, visit)
        for v in stale:
            heapq.heappush(heap, (-fresh[v], v, len(seeds)))
            best = min(best or (-fresh[v], v), (-fresh[v], v))
    return seeds, visits
