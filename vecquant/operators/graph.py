"""Proximity graphs on shards: bounded degree, pruned, searched best-first.

A shard is a bounded slice of the set by a hash of the id; each is built and searched in one
task, and the shards' results are merged. Searches run in lock-step over many queries at once:
a step expands one row a query, and only rows not met before are measured.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.operators.pq import codes_matrix, decode_codes
from vecquant.operators.prep import lists, matrix
from vecquant.operators.search import TOPK, collect_queries, rank_rows

#: Marks of rows met that a lock-step search may hold.
_MARKS = 64_000_000
#: Rows of a shard up to which its build measures all pairs once: 32 MB of squared distances.
_PAIRED = 2_000


def beam(x: np.ndarray, neighbours: np.ndarray, start: int, q: np.ndarray, window: int, known: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The rows nearest to each query that a search from the start meets, best first.

    neighbours: [rows, degree], -1 where a row has fewer. Gives places and squared distances
    [queries, window], -1 and infinity where fewer are met, and how many each query measured.
    known: squared distances [queries, rows], where they have been measured before.
    """
    n, count = len(x), len(q)
    at_once = max(1, _MARKS // max(1, n))
    if count > at_once:
        parts = [beam(x, neighbours, start, q[a : a + at_once], window, None if known is None else known[a : a + at_once]) for a in range(0, count, at_once)]
        return tuple(np.concatenate(p) for p in zip(*parts, strict=True))
    squares = (x**2).sum(axis=1)
    own = (q**2).sum(axis=1)
    met = np.zeros((count, n), dtype=bool)
    met[:, start] = True
    # A held row's place, doubled, and one more where it has not been expanded; -2 where nothing is held.
    state = np.full((count, window), -2, dtype=np.int64)
    far = np.full((count, window), np.inf)
    state[:, 0], far[:, 0] = 2 * start + 1, squares[start] - 2 * (q @ x[start]) + own if known is None else known[:, start]
    active = np.arange(count)
    while len(active):
        first = (state[active] & 1).argmax(axis=1)
        at = state[active, first]
        going = (at & 1).astype(bool)
        active, first, at = active[going], first[going], at[going]
        if not len(active):
            break
        state[active, first] = at - 1
        around = neighbours[at >> 1]
        who, slot = np.nonzero((around >= 0) & ~met[active[:, None], around])
        rows, asked = around[who, slot], active[who]
        met[asked, rows] = True
        new = squares[rows] - 2 * np.einsum("nd,nd->n", x[rows], q[asked]) + own[asked] if known is None else known[asked, rows]
        # What is no nearer than the last of a full window would leave it at once; queries that gain nothing stay as they are.
        gained = np.flatnonzero(new < far[asked, -1])
        if not len(gained):
            continue
        who, rows, new = who[gained], rows[gained], new[gained]
        each = np.bincount(who)
        changed = np.flatnonzero(each)
        each = each[changed]
        line, column = np.repeat(np.arange(len(changed)), each), np.arange(len(who)) - np.repeat(np.cumsum(each) - each, each) + window
        some = active[changed]
        every, states = np.full((len(some), window + each.max()), np.inf), np.full((len(some), window + each.max()), -2, dtype=np.int64)
        every[:, :window], states[:, :window] = far[some], state[some]
        every[line, column], states[line, column] = new, 2 * rows + 1
        # The held rows are in order already, which a stable sort makes use of; of equal ones the first met stays.
        order = np.argsort(every, axis=1, kind="stable")[:, :window]
        order += np.arange(len(some))[:, None] * every.shape[1]
        far[some], state[some] = every.ravel().take(order), states.ravel().take(order)
    return state >> 1, np.where(np.isfinite(far), np.maximum(far, 0), np.inf), met.sum(axis=1)


def prune(x: np.ndarray, row: int, candidates: np.ndarray, degree: int, alpha: float, known: np.ndarray | None = None) -> np.ndarray:
    """Neighbours of a row: nearest first, none that a kept one is alpha times nearer to. known: squared distances of all pairs."""
    candidates = np.sort(candidates[(candidates != row) & (candidates >= 0)])
    if not len(candidates):
        return candidates
    candidates = candidates[np.concatenate([[True], candidates[1:] != candidates[:-1]])]
    d = np.sqrt(((x[candidates] - x[row]) ** 2).sum(axis=1) if known is None else known[row, candidates])
    order = np.argsort(d, kind="stable")
    candidates, d = candidates[order], d[order]
    near = x[candidates] if known is None else None
    squares = None if near is None else (near**2).sum(axis=1)
    alive, kept = np.ones(len(candidates), dtype=bool), []
    i = 0
    while len(kept) < degree:
        kept.append(i)
        # Only a kept row's distances are asked for.
        between = known[candidates[i]].take(candidates) if near is None else np.maximum(squares - 2 * (near @ near[i]) + squares[i], 0)
        alive &= np.sqrt(between) * alpha > d
        alive[: i + 1] = False
        i = int(alive.argmax())
        if not alive[i]:
            break
    return candidates[kept]


def _put(neighbours: np.ndarray, row: int, own: np.ndarray) -> None:
    neighbours[row, : len(own)] = own
    neighbours[row, len(own) :] = -1


def build_rows(x: np.ndarray, degree: int = 64, window: int = 200, alpha: float = 1.2, seed: int = 0, rounds: int = 8) -> tuple[np.ndarray, int]:
    """Neighbours [rows, degree] (-1 where fewer) and the start row (nearest the middle).

    Two passes, without and with slack. In a pass rows are taken in random order in rounds: a
    round searches the graph as it stands, prunes its rows, then the rows that they point to.
    """
    n = len(x)
    rng = np.random.Generator(np.random.Philox(seed))
    start = int(((x - x.mean(axis=0)) ** 2).sum(axis=1).argmin())
    known = None
    if n <= _PAIRED:
        squares = (x**2).sum(axis=1)
        known = np.maximum(squares[:, None] - 2 * (x @ x.T) + squares[None, :], 0)
    neighbours = np.full((n, degree), -1, dtype=np.int64)
    for row in range(n if n > 1 else 0):
        chosen = rng.choice(n - 1, min(degree, n - 1), replace=False)
        _put(neighbours, row, chosen + (chosen >= row))
    for slack in (1.0, alpha):
        for some in np.array_split(rng.permutation(n), max(1, min(n, rounds))):
            met, _, _ = beam(x, neighbours, start, x[some], window, None if known is None else known[some])
            sources, targets = [], []
            for row, found in zip(some.tolist(), met, strict=True):
                own = prune(x, row, np.concatenate([found, neighbours[row]]), degree, slack, known)
                _put(neighbours, row, own)
                sources.append(np.full(len(own), row))
                targets.append(own)
            source, target = np.concatenate(sources), np.concatenate(targets)
            order = np.lexsort((source, target))
            source, target = source[order], target[order]
            for part in np.split(np.arange(len(target)), np.flatnonzero(np.diff(target)) + 1) if len(target) else []:
                row = int(target[part[0]])
                back = np.union1d(neighbours[row][neighbours[row] >= 0], source[part])
                _put(neighbours, row, back if len(back) <= degree else prune(x, row, back, degree, slack, known))
    return neighbours, start


def shards_for(rows: int, rows_a_shard: int = 100_000) -> int:
    """Shards, so that none has many more rows than one task is to hold."""
    return max(1, -(-rows // rows_a_shard))


def _vectors(table: pa.Table, book: np.ndarray | None) -> np.ndarray:
    """The rows of a shard, given as they are or by product codes."""
    return matrix(table["embedding"]) if book is None else decode_codes(codes_matrix(table["pq"]), book)


def build(df: DataFrame, shards: int | None = None, degree: int = 64, window: int = 200, alpha: float = 1.2, seed: int = 0, rows_a_shard: int = 100_000, book: np.ndarray | None = None) -> DataFrame:
    """shard, vec_id, embedding, neighbors (ids), entry: whether search starts here.

    Without a number of shards, they follow the number of rows, and a shard stays bounded. With a
    codebook, rows are product codes (pq) and stay such in the index: the graph is over the vectors that they stand for.
    """
    shards = shards or shards_for(df.count(), rows_a_shard)
    shipped = None if book is None else df.sparkSession.sparkContext.broadcast(book)

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("vec_id")
        ids, x = table["vec_id"].to_numpy(), _vectors(table, shipped and shipped.value)
        found, start = build_rows(x, degree, window, alpha, seed)
        named = pa.array([ids[v[v >= 0]] for v in found], pa.list_(pa.int64()))
        rows = {"embedding": lists(x, pa.float64())} if shipped is None else {"pq": table["pq"]}
        return pa.table({"shard": table["shard"], "vec_id": table["vec_id"], **rows, "neighbors": named, "entry": pa.array(np.arange(len(ids)) == start)})

    vector = F.transform("embedding", lambda v: v.cast("double")).alias("embedding") if book is None else F.col("pq")
    rows = df.select(F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int").alias("shard"), "vec_id", vector)
    kind = "embedding array<double>" if book is None else "pq binary"
    return rows.groupBy("shard").applyInArrow(run, f"shard int, vec_id long, {kind}, neighbors array<long>, entry boolean")


def search(index: DataFrame, queries: DataFrame, k: int, window: int = 200, book: np.ndarray | None = None) -> DataFrame:
    """query_id, vec_id, score (dot), rank: every shard is searched and the results are merged. book: that of an index of product codes."""
    names, q = collect_queries(queries)
    shipped = index.sparkSession.sparkContext.broadcast((q, book))

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("vec_id")
        q, book = shipped.value
        ids, x = table["vec_id"].to_numpy(), _vectors(table, book)
        around = table["neighbors"].combine_chunks()
        sizes = np.diff(around.offsets.to_numpy())
        neighbours = np.full((len(ids), max(1, int(sizes.max(initial=0)))), -1, dtype=np.int64)
        neighbours[np.repeat(np.arange(len(ids)), sizes), np.concatenate([np.arange(s) for s in sizes] or [np.zeros(0, dtype=np.int64)])] = np.searchsorted(ids, around.flatten().to_numpy())
        start = int(np.flatnonzero(table["entry"].to_numpy())[0])
        known = None
        if len(ids) <= _PAIRED and len(ids) * len(q) <= _MARKS // 8:
            known = (x**2).sum(axis=1) - 2 * (q @ x.T) + (q**2).sum(axis=1)[:, None]
        met, _, _ = beam(x, neighbours, start, q, max(window, k), known)
        at, slot = np.nonzero(met[:, :k] >= 0)
        rows = met[at, slot]
        return pa.table({"query_id": pa.array(names[at]), "vec_id": pa.array(ids[rows]), "score": pa.array(np.einsum("nd,nd->n", x[rows], q[at]))})

    return rank_rows(index.groupBy("shard").applyInArrow(run, TOPK), k)


def degrees(index: DataFrame) -> DataFrame:
    return index.groupBy("shard").agg(F.count("*").alias("n"), F.avg(F.size("neighbors")).alias("mean_degree"), F.max(F.size("neighbors")).alias("most"))


def node_bytes(index: DataFrame) -> DataFrame:
    """vec_id, bytes of a node's neighbour list: a count and a place of 4 bytes each."""
    return index.select("vec_id", (4 * (F.size("neighbors") + 1)).cast("long").alias("bytes"))


__all__ = ["beam", "build", "build_rows", "degrees", "node_bytes", "prune", "search", "shards_for"]
