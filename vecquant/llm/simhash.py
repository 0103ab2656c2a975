"""SimHash fingerprints and their links, by a Gray-ordered index over masked bit patterns.

Upper nodes of the index are masked patterns: the bits are cut into blocks, and two
fingerprints that differ in few bits agree on some choice of blocks, so each fingerprint stands
under one node for every choice. Under a node, fingerprints are sorted by Gray rank; runs of
them form groups that keep the bits all members share, and a pair of groups is left out as soon
as the differences between their shared bits add up past the limit. Only links that join parts
still apart are passed on: a spanning forest, not all pairs.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecquant.llm import shingles
from vecquant.llm.common import cut_lineage, saved, single_column, text_slices
from vecquant.llm.components import smallest_reachable

BITS = 64
_GROUP = 32


def fingerprint(text: str, width: int = 4) -> int:
    """Bits set in over half of the hashes of all word shingles; 0 for a text without words."""
    return int(_fingerprints([text], width)[0])


def _fingerprints(texts: list[str], width: int) -> np.ndarray:
    out = np.zeros(len(texts), dtype=np.uint64)
    powers = np.uint64(1) << np.arange(BITS, dtype=np.uint64)
    hash_ = xxhash.xxh64_intdigest
    for k, text in enumerate(texts):
        words = text.encode().lower().split()
        if not words:
            continue
        n = max(1, len(words) - width + 1)
        joined = b" ".join(words)
        if n == 1:
            hashes = np.array([hash_(joined, 42)], dtype=np.uint64)
        else:
            ends = np.cumsum([len(w) + 1 for w in words]) - 1
            starts = [0, *(ends[: n - 1] + 1).tolist()]
            hashes = np.array([hash_(joined[a:b], 42) for a, b in zip(starts, ends[width - 1 :].tolist(), strict=True)], dtype=np.uint64)
        counts = np.zeros(BITS, dtype=np.int64)
        for i in range(0, n, 65_536):
            bits = np.unpackbits(hashes[i : i + 65_536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            counts += bits.sum(axis=0, dtype=np.int64)
        out[k] = powers[2 * counts > n].sum(dtype=np.uint64)
    return out


def fingerprints(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", width: int = 4) -> DataFrame:
    """doc_id, code (the fingerprint's bits as a long). A null text has no words, so code 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_slices(batches, "text"):
            codes = _fingerprints(texts, width).view(np.int64)
            yield pa.RecordBatch.from_arrays([single_column(batch, "doc_id"), pa.array(codes)], names=["doc_id", "code"])

    kind = docs.schema[id_column].dataType.simpleString()
    source = docs.select(F.col(id_column).alias("doc_id"), F.col(text_column).alias("text"))
    return source.mapInArrow(run, f"doc_id {kind}, code long")


def gray_rank(code: Column) -> Column:
    """Place of the code in the reflected Gray sequence."""
    for k in (1, 2, 4, 8, 16, 32):
        code = code.bitwiseXOR(F.shiftrightunsigned(code, k))
    return code


def masks(blocks: int, shared: int) -> list[int]:
    """A mask of bits for every choice of `shared` of `blocks` blocks of nearly equal size."""
    ends = [BITS * i // blocks for i in range(blocks + 1)]
    block = [((1 << (b - a)) - 1) << a for a, b in zip(ends, ends[1:], strict=False)]
    return [sum(chosen) for chosen in combinations(block, shared)]


def _signed(mask: int) -> int:
    return mask - (1 << BITS) if mask >> (BITS - 1) else mask


def _find(parent: np.ndarray, x: int) -> int:
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def _union_pairs(left: np.ndarray, right: np.ndarray, n: int, parent: np.ndarray) -> list[tuple[int, int]]:
    """Pairs that join parts still apart; the parts are joined."""
    kept = []
    for a, b in zip(left.tolist(), right.tolist(), strict=True):
        ra, rb = _find(parent, a), _find(parent, b)
        if ra != rb:
            parent[max(ra, rb)] = min(ra, rb)
            kept.append((a, b))
    return kept


def near_pairs(codes: np.ndarray, limit: int, other: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places of all pairs within limit bits, in portions; codes in Gray order.

    With other, pairs between the two lists; else pairs within the first, each once.
    """
    lists = [codes, codes if other is None else other]
    nodes = []
    for part in lists:
        cuts = np.arange(0, len(part), _GROUP)
        all_, any_ = np.bitwise_and.reduceat(part, cuts), np.bitwise_or.reduceat(part, cuts)
        nodes.append((cuts, ~(all_ ^ any_), all_))  # bits that all members share, and their values
    (cut_a, same_a, bits_a), (cut_b, same_b, bits_b) = nodes
    for i in range(len(cut_a)):
        first = i if other is None else 0
        apart = np.bitwise_count((bits_a[i] ^ bits_b[first:]) & same_a[i] & same_b[first:])
        partners = first + np.flatnonzero(apart <= limit)
        rows = np.arange(cut_a[i], min(cut_a[i] + _GROUP, len(lists[0])))
        for some in np.array_split(partners, max(1, len(partners) // 512)):
            if not len(some):
                continue
            columns = (cut_b[some][:, None] + np.arange(_GROUP)).ravel()
            columns = columns[columns < len(lists[1])]
            near = np.bitwise_count(lists[0][rows][:, None] ^ lists[1][columns][None, :]) <= limit
            a, b = np.nonzero(near)
            a, b = rows[a], columns[b]
            if other is None:
                a, b = a[a < b], b[a < b]
            yield a, b


def _links_of_node(codes: np.ndarray, side: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Links of one node's codes that join parts still apart. side: 0 and 1 of a tile of two chunks."""
    parent = np.arange(len(codes))
    kept: list[tuple[int, int]] = []
    first = np.flatnonzero(side == 0)
    second = np.flatnonzero(side == 1)
    if len(second):
        for a, b in near_pairs(codes[first], limit, codes[second]):
            kept += _union_pairs(first[a], second[b], len(codes), parent)
    else:
        for a, b in near_pairs(codes, limit):
            kept += _union_pairs(a, b, len(codes), parent)
    pairs = np.array(kept, dtype=np.int64).reshape(-1, 2)
    return codes[pairs[:, 0]], codes[pairs[:, 1]]


def _runs(key: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    cuts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
    return cuts, np.diff(np.append(cuts, len(key)))


def _node_links(batches: Iterator[pa.RecordBatch], limit: int) -> Iterator[pa.RecordBatch]:
    """Links within runs of equal (mask, node, tile) over rows sorted by them and by Gray rank."""

    def out(pairs: list[tuple[np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        a = np.concatenate([p[0] for p in pairs]) if pairs else np.zeros(0, dtype=np.uint64)
        b = np.concatenate([p[1] for p in pairs]) if pairs else np.zeros(0, dtype=np.uint64)
        return pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    held: list[np.ndarray] = []

    def close(rows: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray]]:
        table = np.concatenate(rows, axis=1)
        tile = table[:3]
        edge = np.concatenate([[True], (tile[:, 1:] != tile[:, :-1]).any(axis=0)])
        cuts = np.flatnonzero(edge)
        sizes = np.diff(np.append(cuts, table.shape[1]))
        codes, side = table[3].view(np.uint64), table[4]
        found = []
        pair = cuts[sizes == 2]
        if len(pair):
            near = np.bitwise_count(codes[pair] ^ codes[pair + 1]) <= limit
            found.append((codes[pair][near], codes[pair + 1][near]))
        for at, n in zip(cuts[sizes > 2].tolist(), sizes[sizes > 2].tolist(), strict=True):
            found.append(_links_of_node(codes[at : at + n], side[at : at + n], limit))
        return found

    size = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        table = np.stack([single_column(batch, c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("mask", "node", "tile", "code", "side")])
        changes = np.flatnonzero((table[:3, 1:] != table[:3, :-1]).any(axis=0)) + 1
        new_start = bool(held) and (held[-1][:3, -1] != table[:3, 0]).any()
        if held and (new_start or len(changes)) and size > 200_000:
            cut = 0 if new_start else int(changes[0])
            yield out(close([*held, table[:, :cut]]))
            held, table, size = [], table[:, cut:], 0
        held.append(table)
        size += table.shape[1]
    if held:
        yield out(close(held))


def index_shape(codes: int, limit: int) -> tuple[int, int]:
    """(blocks, shared): the fewest shared blocks that leave a node about 256 codes, if codes are spread evenly.

    Every shape finds every pair; more shared blocks mean smaller nodes and more of them.
    """
    for shared in range(1, 5):
        blocks = limit + shared
        if codes >> (BITS * shared // blocks) <= 256:
            break
    return blocks, shared


def link_codes(codes: DataFrame, limit: int = 4, blocks: int | None = None, shared: int | None = None, node_rows: int = 20_000) -> DataFrame:
    """Links a, b between distinct codes (column code) within limit bits: a spanning forest of them.

    Any two codes within limit bits are connected through the links that come back.
    blocks - limit >= shared makes sure that each near pair stands under a common node; without
    them the shape follows the number of codes. A node with more than node_rows codes is cut into
    chunks by a hash of the code, and each pair of chunks is a tile of its own, so that no task
    holds more than two chunks of one node.
    """
    if blocks is None or shared is None:
        blocks, shared = index_shape(codes.count(), limit)
    if blocks - limit < shared:
        raise ValueError("blocks - limit must be at least shared")
    chosen = [_signed(m) for m in masks(blocks, shared)]
    under = codes.select("code", F.explode(F.array(*[F.struct(F.lit(i).alias("mask"), F.col("code").bitwiseAND(F.lit(m)).alias("node")) for i, m in enumerate(chosen)])).alias("k"))
    under = under.select("k.mask", "k.node", "code")
    # Large nodes are few: at most masks * codes / node_rows.
    big = cut_lineage(under.groupBy("mask", "node").agg(F.count("*").alias("n")).where(F.col("n") > node_rows))
    plain = under.withColumns({"tile": F.lit(0).cast("long"), "side": F.lit(0).cast("long")})
    if not big.isEmpty():
        # Chunks by a hash of the code, tiles by pairs of chunks.
        chunks = F.ceil(F.col("n") / node_rows).cast("long")
        joined = under.join(big, ["mask", "node"], "left")
        own = F.pmod(F.xxhash64("code"), F.col("chunks"))
        tiled = joined.where(F.col("n").isNotNull()).withColumn("chunks", chunks).withColumn("own", own)
        spots = F.transform(
            F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1),
            lambda k: F.struct(
                (F.least("own", k) * F.col("chunks") + F.greatest("own", k)).alias("tile"), (F.col("own") > k).cast("long").alias("side")
            ),
        )
        tiled = tiled.select("mask", "node", "code", F.explode(spots).alias("t"))
        plain = joined.where(F.col("n").isNull()).select("mask", "node", "code", F.lit(0).cast("long").alias("tile"), F.lit(0).cast("long").alias("side"))
        plain = plain.unionByName(tiled.select("mask", "node", "code", "t.tile", "t.side"))
    ordered = plain.withColumn("gray", gray_rank(F.col("code")))
    ordered = ordered.repartition("mask", "node", "tile").sortWithinPartitions("mask", "node", "tile", "gray")
    rows = ordered.select(F.col("mask").cast("long").alias("mask"), "node", "tile", "code", "side")
    return rows.mapInArrow(lambda b: _node_links(b, limit), "a long, b long")


def near_duplicates(
    docs: DataFrame,
    id_column: str = "doc_id",
    text_column: str = "text",
    limit: int = 4,
    width: int = 4,
) -> DataFrame:
    """doc_id, fingerprint (hex), component_id: the smallest id reached by links of near fingerprints.

    Every row stays. Documents without words (empty and null texts) share the fingerprint zero
    and link like others. Repeated ids are one node; a null id gets the smallest id of its
    fingerprint's component, or null. An empty table gives no rows. Ids are integers.
    """
    prints = cut_lineage(fingerprints(docs, id_column, text_column, width))
    rows = _components(prints, lambda codes: link_codes(codes, limit))
    hexed = F.lower(F.lpad(F.hex("code"), 16, "0"))
    return rows.select(F.col("doc_id").alias(id_column), hexed.alias("fingerprint"), "component_id")


def _components(prints: DataFrame, links_of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """doc_id, code, component_id of every row of prints (doc_id, code), by links between distinct codes."""
    prints = prints.select("doc_id", "code")
    lowest = prints.groupBy("code").agg(F.min("doc_id").alias("least_id"))
    lowest = cut_lineage(lowest)
    parts = smallest_reachable(links_of(lowest.select("code")))
    known = lowest.join(parts, lowest.code == parts.node, "left").select("code", "least_id", F.coalesce("component", "code").alias("part"))
    # A document that has several fingerprints (a repeated id) ties their parts together.
    repeated = prints.where("doc_id is not null").groupBy("doc_id").agg(F.min("code").alias("a"), F.max("code").alias("b")).where("a <> b")
    if not repeated.isEmpty():
        ties = prints.join(repeated.select("doc_id", "a"), "doc_id").select("a", F.col("code").alias("b"))
        links = ties.union(known.select(F.col("code").alias("a"), F.col("part").alias("b")))
        parts = smallest_reachable(links)
        known = lowest.join(parts, lowest.code == parts.node, "left").select("code", "least_id", F.coalesce("component", "code").alias("part"))
    # Written first, so that a part with very many codes can be split in the join.
    known = cut_lineage(known)
    roots = cut_lineage(known.groupBy("part").agg(F.min("least_id").alias("component_id")))
    by_code = known.join(roots, "part").select("code", "component_id")
    return prints.join(by_code, "code", "left").select("doc_id", "code", "component_id")


def _all_prints(docs: DataFrame, id_column: str, text_column: str) -> DataFrame:
    """doc_id, row (hash of the text), code (of the set of 5-word shingles), keys, print (4-word fingerprint) in one pass."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_slices(batches, "text", 1_000_000):
            sets = [shingles.shingle_set(t) for t in texts]
            own = np.array([shingles.set_code(s) for s in sets], dtype=np.uint64).view(np.int64)
            found = pa.array([shingles.keys(s).view(np.int64) if len(s) else [] for s in sets], pa.list_(pa.int64()))
            columns = [single_column(batch, "doc_id"), single_column(batch, "row"), pa.array(own), found, pa.array(_fingerprints(texts, 4).view(np.int64))]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "row", "code", "keys", "print"])

    kind = docs.schema[id_column].dataType.simpleString()
    source = docs.select(F.col(id_column).alias("doc_id"), F.col(text_column).alias("text"), F.xxhash64(text_column).alias("row"))
    return source.mapInArrow(run, f"doc_id {kind}, row long, code long, keys array<long>, print long")


def _similar(docs: DataFrame, id_column: str, text_column: str, limit: int) -> tuple[DataFrame, DataFrame]:
    """Members and roots (see _grouped) by sets of 5-word shingles, linked by similarity and by near fingerprints."""
    prints = saved(_all_prints(docs, id_column, text_column))
    reps = cut_lineage(prints.groupBy("print").agg(F.min("code").alias("rep"), F.max("code").alias("last")))
    near = link_codes(reps.select(F.col("print").alias("code")), limit)
    by_print = reps.select(F.col("print").alias("a"), F.col("rep").alias("b"))
    ends = near.join(by_print.withColumnRenamed("b", "x"), "a").select("x", F.col("b").alias("a")).join(by_print, "a").select(F.col("x").alias("a"), "b")
    # Prints of one set alone have nothing to add.
    common = prints.select("print", "code").join(reps.where("rep <> last").select("print", "rep"), "print").select(F.col("code").alias("a"), F.col("rep").alias("b"))
    return _grouped(prints, shingles.links(docs, prints, text_column).union(ends).union(common))


def _near(docs: DataFrame, id_column: str, text_column: str, limit: int, width: int) -> tuple[DataFrame, DataFrame]:
    """Members and roots (see _grouped) by fingerprints, linked where they are near."""
    named = docs.select(F.struct(F.col(id_column).alias("doc_id"), F.xxhash64(text_column).alias("row")).alias("name"), F.col(text_column).alias("text"))
    prints = saved(fingerprints(named, "name", "text", width).select("doc_id.doc_id", "doc_id.row", "code"))
    return _grouped(prints, link_codes(prints.select("code").distinct(), limit))


def _grouped(prints: DataFrame, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """doc_id, row, part (a number of its group) of every row of prints; part, component_id (its smallest id). Both written."""
    repeated = prints.where("doc_id is not null").groupBy("doc_id").agg(F.min("code").alias("a"), F.max("code").alias("b")).where("a <> b")
    repeated = cut_lineage(repeated)
    if not repeated.isEmpty():  # a document that has several texts ties their groups together
        edges = edges.union(prints.join(repeated.select("doc_id", "a"), "doc_id").select("a", F.col("code").alias("b")))
    parts = smallest_reachable(edges)
    members = prints.select("doc_id", "row", "code").join(parts, F.col("code") == F.col("node"), "left")
    members = saved(members.select("doc_id", "row", F.coalesce("component", "code").alias("part")))
    return members, cut_lineage(members.groupBy("part").agg(F.min("doc_id").alias("component_id")))


def similar_documents(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", limit: int = 4) -> DataFrame:
    """doc_id, component_id: the smallest id reached by links of 5-word Jaccard similarity 0.8 or more, or of fingerprints within limit bits.

    Rows without words, repeated ids and null ids are treated as near_duplicates treats them.
    """
    members, roots = _similar(docs, id_column, text_column, limit)
    return members.join(roots, "part").select(F.col("doc_id").alias(id_column), "component_id")


def keep_one_similar(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", limit: int = 4) -> DataFrame:
    """The rows of docs without near duplicates, by groups as similar_documents has them: of each the row with the smallest id.

    Of repeated rows with that id one stays (the text that hashes lowest). Rows with a null id
    stay only where no member of their group has an id, one per group.
    """
    return _keep_one(docs, id_column, text_column, lambda source, key, text: _similar(source, key, text, limit))


def _keep_one(docs: DataFrame, id_column: str, text_column: str, grouped: Callable[[DataFrame, str, str], tuple[DataFrame, DataFrame]]) -> DataFrame:
    names = [f"c{i}" for i in range(len(docs.columns))]
    key, text = names[docs.columns.index(id_column)], names[docs.columns.index(text_column)]
    source = docs.toDF(*names)
    return _rows_of(source, key, text, *grouped(source, key, text)).toDF(*docs.columns)


#: Ids that a broadcast may hold (8 bytes each); more go through a shuffle.
BROADCAST_IDS = 1_000_000


def _few(ids: DataFrame) -> DataFrame:
    return F.broadcast(ids) if ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS else ids


def _rows_of(source: DataFrame, key: str, text: str, members: DataFrame, roots: DataFrame) -> DataFrame:
    """One row of source a group. Ids are settled first, so that texts move once, or not at all where few ids go."""
    gone = members.join(roots, "part").where("doc_id is not null and doc_id <> component_id").select("doc_id").distinct()
    twice = members.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    gone, twice = saved(gone), saved(twice)
    out = _few(gone.union(twice).select(F.col("doc_id").alias("gone"))) if not twice.isEmpty() else _few(gone.select(F.col("doc_id").alias("gone")))
    kept = source.where(F.col(key).isNotNull()).join(out, F.col(key) == F.col("gone"), "left_anti")
    if not twice.isEmpty():
        own = source.join(_few(twice.join(gone, "doc_id", "left_anti")), F.col(key) == F.col("doc_id"), "left_semi")
        order = F.struct(F.xxhash64(F.coalesce(text, F.lit(""))), *[F.xxhash64(n) for n in source.columns])
        firsts = own.groupBy(key).agg(F.min_by(F.struct(*source.columns), order).alias("first"))
        kept = kept.unionByName(firsts.select("first.*"))
    alone = members.join(roots, "part").where("doc_id is null and component_id is null")
    alone = saved(alone.groupBy("part").agg(F.min("row").alias("row")).select(F.col("row").alias("own")).distinct())
    if not alone.isEmpty():
        own = source.where(F.col(key).isNull()).withColumn("hash", F.xxhash64(text)).join(alone, F.col("hash") == F.col("own"), "left_semi")
        kept = kept.unionByName(own.dropDuplicates(["hash"]).drop("hash"))
    return kept


def keep_one_per_group(
    docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", limit: int = 4, width: int = 4
) -> DataFrame:
    """keep_one_similar with groups by near fingerprints alone, as near_duplicates has them."""
    return _keep_one(docs, id_column, text_column, lambda source, key, text: _near(source, key, text, limit, width))
