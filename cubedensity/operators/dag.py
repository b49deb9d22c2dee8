"""Tile graph, colorings, critical path, schedules and replication: planning on tiles, not on events.

Tiles number at most a few hundred thousand, so plans are made on the driver from tile loads; the coloring and the
critical path have DataFrame twins for more tiles than that.
"""

from __future__ import annotations

import heapq
import math
from dataclasses import dataclass
from itertools import product

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cubedensity.plans.durable import durable
from cubedensity.spec import TileSpec

DRIVER_TILES = 1 << 18
STEPS = [s for s in product((-1, 0, 1), repeat=3) if any(s)]


def check_tiles(tiles: TileSpec) -> None:
    if tiles.total > DRIVER_TILES:
        raise ValueError(f"{tiles.total} tiles are planned with greedy_colors_df and critical_path_df, not on the driver")


def number(tile: tuple[int, int, int], tiles: TileSpec) -> int:
    return (tile[0] * tiles.b + tile[1]) * tiles.c + tile[2]


def place(tile_id: int, tiles: TileSpec) -> tuple[int, int, int]:
    return tile_id // (tiles.b * tiles.c), tile_id // tiles.c % tiles.b, tile_id % tiles.c


def neighbours(tile_id: int, tiles: TileSpec) -> list[int]:
    a, b, c = place(tile_id, tiles)
    near = ((a + i, b + j, c + k) for i, j, k in STEPS)
    return [number(t, tiles) for t in near if all(0 <= v < n for v, n in zip(t, tiles.counts))]


def tile_table(spark: SparkSession, tiles: TileSpec) -> DataFrame:
    i = F.col("id")
    return spark.range(tiles.total).select(
        i.alias("tile_id"),
        F.floor(i / (tiles.b * tiles.c)).cast("int").alias("a"),
        F.pmod(F.floor(i / tiles.c), F.lit(tiles.b)).cast("int").alias("b"),
        F.pmod(i, F.lit(tiles.c)).cast("int").alias("c"),
    )


def tile_graph(spark: SparkSession, tiles: TileSpec) -> DataFrame:
    """``(src, dst)``: all ordered pairs of adjacent tiles, 26 for an inner tile."""
    steps = F.array(*(F.struct(*(F.lit(v).alias(n) for v, n in zip(s, "ijk"))) for s in STEPS))
    far = tile_table(spark, tiles).select("*", F.explode(steps).alias("s"))
    a, b, c = F.col("a") + F.col("s.i"), F.col("b") + F.col("s.j"), F.col("c") + F.col("s.k")
    ok = a.between(0, tiles.a - 1) & b.between(0, tiles.b - 1) & c.between(0, tiles.c - 1)
    return far.filter(ok).select(F.col("tile_id").alias("src"), ((a.cast("long") * tiles.b + b) * tiles.c + c).alias("dst"))


def parity(tile_id: int, tiles: TileSpec) -> int:
    """One of eight sets, by the parity of the tile's place along each axis."""
    a, b, c = place(tile_id, tiles)
    return (a % 2) * 4 + (b % 2) * 2 + c % 2


def parity_colors(tiles: TileSpec) -> dict[int, int]:
    check_tiles(tiles)
    return {t: parity(t, tiles) for t in range(tiles.total)}


def visiting_order(loads: dict[int, int], tiles: TileSpec, order: str) -> list[int]:
    every = range(tiles.total)
    if order == "load":
        return sorted(every, key=lambda t: (-loads.get(t, 0), t))
    if order == "parity":
        return sorted(every, key=lambda t: (parity(t, tiles), t))
    if order == "natural":
        return list(every)
    raise ValueError(f"no order {order!r}")


def _padded(tiles: TileSpec) -> tuple[list[int], list[int]]:
    """Place of each tile in a box with a rim, and the steps to its neighbours there: no tile needs to test for borders."""
    b, c = tiles.b + 2, tiles.c + 2
    at = [((i + 1) * b + j + 1) * c + k + 1 for i in range(tiles.a) for j in range(tiles.b) for k in range(tiles.c)]
    return at, [(i * b + j) * c + k for i, j, k in STEPS]


def greedy_colors(loads: dict[int, int], tiles: TileSpec, order: str = "load") -> dict[int, int]:
    """Each tile in turn takes the least color that none of its neighbours has; 27 colors at most."""
    check_tiles(tiles)
    at, steps = _padded(tiles)
    bit = [0] * ((tiles.a + 2) * (tiles.b + 2) * (tiles.c + 2))
    colors: dict[int, int] = {}
    for t in visiting_order(loads, tiles, order):
        here, used = at[t], 0
        for s in steps:
            used |= bit[here + s]
        free = ~used & (used + 1)
        bit[here] = free
        colors[t] = free.bit_length() - 1
    return colors


def greedy_colors_df(spark: SparkSession, loads: DataFrame, tiles: TileSpec) -> DataFrame:
    """The same coloring by load, in rounds: a tile is colored once all neighbours that go before it are."""
    ranked = tile_table(spark, tiles).select("tile_id").join(loads.select("tile_id", "load"), "tile_id", "left").fillna(0, ["load"])
    rank = F.struct((-F.col("load")).alias("l"), F.col("tile_id").alias("t"))
    ranked = durable(ranked.select("tile_id", rank.alias("rank")))
    before = durable(
        tile_graph(spark, tiles)
        .join(ranked.select(F.col("tile_id").alias("src"), F.col("rank").alias("r")), "src")
        .join(ranked.select(F.col("tile_id").alias("dst"), F.col("rank").alias("s")), "dst")
        .filter("s < r")
        .select("src", "dst")
    )
    done = durable(ranked.join(before, F.col("tile_id") == F.col("src"), "left_anti").select("tile_id", F.lit(0).alias("color")))
    while True:
        left = ranked.select("tile_id").join(done, "tile_id", "left_anti")
        seen = before.join(done.withColumnRenamed("tile_id", "dst"), "dst", "left").groupBy("src").agg(
            F.collect_set("color").alias("used"), F.count_if(F.col("color").isNull()).alias("open")
        )
        ready = left.join(seen.filter("open = 0"), F.col("tile_id") == F.col("src"))
        free = F.array_min(F.array_except(F.sequence(F.lit(0), F.lit(26)), F.col("used")))
        new = durable(ready.select("tile_id", free.alias("color")))
        if new.isEmpty():
            return done
        done = durable(done.union(new))


def oriented_edges(colors: dict[int, int], tiles: TileSpec) -> list[tuple[int, int]]:
    """Edges of the dependency graph: between neighbours, from the lower to the higher color."""
    return [(t, n) for t in colors for n in neighbours(t, tiles) if n in colors and colors[t] < colors[n]]


def weights_of(loads: dict[int, int], tiles: TileSpec, weight: str = "own") -> dict[int, int]:
    """Task weights: a tile's events, or those of the tile and its neighbours."""
    if weight == "own":
        return {t: loads.get(t, 0) for t in range(tiles.total)}
    if weight == "own_plus_neighbours":
        box = np.zeros(tiles.counts, np.int64)
        for t, n in loads.items():
            box[place(t, tiles)] = n
        wide = np.pad(box, 1)
        total = sum(wide[1 + i : 1 + i + tiles.a, 1 + j : 1 + j + tiles.b, 1 + k : 1 + k + tiles.c] for i, j, k in [(0, 0, 0), *STEPS])
        return dict(enumerate(total.ravel().tolist()))
    raise ValueError(f"no weight {weight!r}")


@dataclass
class Path:
    length: float
    chain: list[int]
    finish: dict[int, float]


class _Chains:
    """Finish of every tile and the neighbour that it waits for, kept up to date while weights change.

    Whole arrays, color after color, at first; then only tiles whose weight or whose neighbour's finish changed.
    """

    def __init__(self, colors: dict[int, int], weights: dict[int, float], tiles: TileSpec):
        self.at, self.steps = _padded(tiles)
        self.tiles, self.colors = tiles, colors
        rim = tuple(n + 2 for n in tiles.counts)
        ids = np.fromiter(colors, np.int64, len(colors))
        place = np.array(self.at, np.int64)[ids]
        color = np.full(math.prod(rim), 99, np.int64)
        color[place] = np.fromiter(colors.values(), np.int64, len(colors))
        weight = np.zeros(math.prod(rim))
        weight[place] = [weights[t] for t in ids.tolist()]
        finish = np.zeros(math.prod(rim))
        for c in sorted(set(colors.values())):
            mine = place[color[place] == c]
            best = np.zeros(len(mine))
            for s in self.steps:
                best = np.maximum(best, np.where(color[mine + s] < c, finish[mine + s], 0.0))
            finish[mine] = best + weight[mine]
        self.of = dict(zip(place.tolist(), ids.tolist()))
        self.color, self.weight, self.finish = color.tolist(), weight.tolist(), finish.tolist()
        self.heap = [(-self.finish[p], t) for p, t in self.of.items()]
        heapq.heapify(self.heap)

    def change(self, weights: dict[int, float]) -> None:
        open_ = []
        for t, w in weights.items():
            p = self.at[t]
            if self.weight[p] != w:
                self.weight[p] = w
                open_.append((self.color[p], p))
        heapq.heapify(open_)
        seen = set()
        while open_:
            c, p = heapq.heappop(open_)
            if p in seen:
                continue
            seen.add(p)
            best = max((self.finish[p + s] for s in self.steps if self.color[p + s] < c), default=0.0)
            now = max(best, 0.0) + self.weight[p]
            if now != self.finish[p]:
                self.finish[p] = now
                heapq.heappush(self.heap, (-now, self.of[p]))
                for s in self.steps:
                    if c < self.color[p + s] < 99:
                        heapq.heappush(open_, (self.color[p + s], p + s))

    def path(self) -> Path:
        """The heaviest chain; ties go to the lower tile."""
        while self.heap and -self.heap[0][0] != self.finish[self.at[self.heap[0][1]]]:
            heapq.heappop(self.heap)  # a finish that has changed since
        if not self.heap:
            return Path(0, [], {})
        chain, p = [], self.at[self.heap[0][1]]
        length = self.finish[p]
        while p is not None:
            chain.append(self.of[p])
            before = [(-self.finish[p + s], self.of[p + s], p + s) for s in self.steps if self.color[p + s] < self.color[p] and self.finish[p + s] > 0]
            p = min(before)[2] if before else None
        number_ = lambda v: int(v) if v == int(v) else v
        return Path(number_(length), chain[::-1], {t: number_(self.finish[q]) for q, t in self.of.items()} if len(self.of) <= 4096 else {})


def critical_path(colors: dict[int, int], weights: dict[int, float], tiles: TileSpec) -> Path:
    """The heaviest chain of the dependency graph; ties go to the lower tile. Finishes of all tiles up to 4,096 of them."""
    return _Chains(colors, weights, tiles).path() if colors else Path(0, [], {})


def critical_path_df(spark: SparkSession, colors: DataFrame, weights: DataFrame, tiles: TileSpec) -> DataFrame:
    """``(tile_id, color, weight, finish)``: one round for each color, on ``colors(tile_id, color)``, ``weights(tile_id, weight)``."""
    nodes = durable(colors.join(weights, "tile_id", "left").fillna(0, ["weight"]).select("tile_id", "color", F.col("weight").cast("long").alias("weight")))
    graph = tile_graph(spark, tiles)
    top = nodes.agg(F.max("color")).first()[0]
    done = durable(nodes.filter("color = 0").withColumn("finish", F.col("weight")))
    for color in range(1, (-1 if top is None else top) + 1):
        now = nodes.filter(F.col("color") == color)
        before = graph.join(done.select(F.col("tile_id").alias("dst"), F.col("finish").alias("f")), "dst").groupBy("src").agg(F.max("f").alias("f"))
        new = now.join(before, F.col("tile_id") == F.col("src"), "left").select("tile_id", "color", "weight", (F.coalesce("f", F.lit(0)) + F.col("weight")).alias("finish"))
        done = durable(done.union(new))
    return done


def graham_bound(total: float, path: float, workers: int) -> float:
    """Longest time that any list schedule can take."""
    return (total - path) / workers + path


def graham_speedup(share: float, workers: int) -> float:
    """Least speedup that a list schedule reaches when the critical path is a share of all work."""
    return 1 / ((1 - share) / workers + share)


def list_schedule(colors: dict[int, int], weights: dict[int, float], tiles: TileSpec, workers: int, priority: str = "load", barrier: bool = False) -> list[tuple[int, int, float, float]]:
    """``(tile, worker, start, end)`` of a greedy run of ready tasks; with ``barrier``, color after color."""
    rank = {t: (-weights[t], t) if priority == "load" else (t,) for t in colors}
    free = [(0.0, w) for w in range(workers)]
    out: list[tuple[int, int, float, float]] = []
    if barrier:
        clock = 0.0
        for color in sorted(set(colors.values())):
            free = [(clock, w) for w in range(workers)]
            for t in sorted((t for t in colors if colors[t] == color), key=rank.__getitem__):
                start, w = heapq.heappop(free)
                out.append((t, w, start, start + weights[t]))
                heapq.heappush(free, (start + weights[t], w))
            clock = max(at for at, _ in free)
        return out
    waits = {t: sum(1 for n in neighbours(t, tiles) if n in colors and colors[n] < colors[t]) for t in colors}
    ready = [(rank[t], t) for t in colors if not waits[t]]
    heapq.heapify(ready)
    running: list[tuple[float, int, int]] = []
    heapq.heapify(free)
    clock = 0.0
    while ready or running:
        while ready and free and free[0][0] <= clock:
            _, w = heapq.heappop(free)
            _, t = heapq.heappop(ready)
            out.append((t, w, clock, clock + weights[t]))
            heapq.heappush(running, (clock + weights[t], t, w))
        clock = running[0][0]
        while running and running[0][0] <= clock:
            end, t, w = heapq.heappop(running)
            heapq.heappush(free, (end, w))
            for n in neighbours(t, tiles):
                if n in colors and colors[n] > colors[t]:
                    waits[n] -= 1
                    if not waits[n]:
                        heapq.heappush(ready, (rank[n], n))
    return out


@dataclass
class Replication:
    copies: dict[int, int]
    path: Path
    rounds: int
    limit: float


def replication_plan(loads: dict[int, int], colors: dict[int, int], tiles: TileSpec, workers: int, weight: str = "own", scope: str = "path", max_rounds: int = 1000) -> Replication:
    """One more copy for the tiles of the critical path until it is at most half a worker's share, or nothing can be copied.

    A tile has no more copies than workers or events; ``scope`` may take in the neighbours of the path's tiles.
    """
    base = weights_of(loads, tiles, weight)
    limit = sum(base.values()) / (2 * workers)
    copies = dict.fromkeys(colors, 1)
    chains = _Chains(colors, {t: base[t] for t in colors}, tiles) if colors else None
    rounds = 0
    while True:
        path = chains.path() if chains else Path(0, [], {})
        if path.length <= limit or rounds >= max_rounds:
            break
        chosen = set(path.chain)
        if scope == "path_and_neighbours":
            chosen |= {n for t in path.chain for n in neighbours(t, tiles)}
        more = [t for t in sorted(chosen) if copies[t] < min(workers, loads.get(t, 0))]
        if not more:
            break
        for t in more:
            copies[t] += 1
        chains.change({t: math.ceil(base[t] / copies[t]) for t in more})
        rounds += 1
    return Replication(copies, path, rounds, limit)
