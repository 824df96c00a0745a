"""Supports of x(#a, #b): how many parents two nodes share, for all pairs of nodes that share enough.

Joining the edges with themselves makes a row for every two children of a parent, nearly all of them for pairs that fall short.  Here
children fall into blocks, each block's edges are packed once, and every two blocks meet in a task of their own, which counts the pairs of a
few children at a time by sorting numbers and gives only those that reach minsup.  No pair is left out and none is looked at twice.

A pair's rows never leave its task, so disk holds the packed edges once for each block (about two bytes an edge), however large the parents.
A task holds two blocks; all edges of one child stand in one block.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..graph import Graph

#: Edges of a block, and how many blocks there are at least.
BLOCK_EDGES, LEAST_BLOCKS = 3_000_000, 8
#: Pairs counted at once: numbers that stay in a core's cache.
AT_ONCE = 250_000


def squeezed(x: np.ndarray) -> bytes:
    """Numbers byte by byte of their places, compressed."""
    planes = np.ascontiguousarray(x.astype("<i4").view(np.uint8).reshape(-1, 4).T)
    return len(x).to_bytes(8, "little") + pa.compress(planes.tobytes(), codec="zstd", asbytes=True)


def unsqueezed(x: bytes) -> np.ndarray:
    n = int.from_bytes(x[:8], "little")
    planes = np.frombuffer(pa.decompress(x[8:], 4 * n, codec="zstd", asbytes=True), np.uint8)
    return np.ascontiguousarray(planes.reshape(4, n).T).view("<i4").ravel()


def written(names: pa.Array) -> bytes:
    sink = pa.BufferOutputStream()
    batch = pa.record_batch([names], ["name"])
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def names_of(x: bytes) -> pa.Array:
    return pa.ipc.open_stream(x).read_all()["name"].combine_chunks()


def one(column: pa.ChunkedArray) -> pa.Array:
    """A column's chunks as one array, with 64-bit offsets where it holds text."""
    if pa.types.is_string(column.type):
        column = column.cast(pa.large_string())
    return pa.concat_arrays(column.chunks)


def pack(edges: pa.Table, minsup: int) -> tuple[bytes, bytes, bytes, bytes] | None:
    """A block's edges without the children that have too few parents: names of parents in order, how many children each has, names of children,
    and the children's numbers parent by parent as differences."""
    src, dst = (one(edges[c]).dictionary_encode() for c in ("src", "dst"))
    p, c = src.indices.to_numpy(), dst.indices.to_numpy()
    enough = np.bincount(c) >= minsup
    mine = enough[c]
    if not mine.any():
        return None
    p, c = p[mine], (np.cumsum(enough) - 1)[c[mine]]
    order = pc.array_sort_indices(src.dictionary).to_numpy()
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    n_children = int(enough.sum())
    key = np.sort(place[p] * n_children + c)
    p, c = key // n_children, key % n_children
    counts = np.bincount(p, minlength=len(order))
    used = np.flatnonzero(counts)
    first = np.r_[True, p[1:] != p[:-1]]
    steps = np.where(first, c, np.diff(c, prepend=0))
    return written(src.dictionary.take(pa.array(order[used]))), squeezed(counts[used]), written(dst.dictionary.filter(pa.array(enough))), squeezed(steps)


class Block:
    """A packed block: parents, where each one's children begin and how many they are, children by number, and their names."""

    def __init__(self, parents: bytes, counts: bytes, names: bytes, steps: bytes):
        self.parents, self.names = names_of(parents), names_of(names)
        self.counts = unsqueezed(counts).astype(np.int64)
        self.starts = np.cumsum(self.counts) - self.counts
        total = np.cumsum(unsqueezed(steps), dtype=np.int64)
        before = np.r_[0, total][self.starts]
        self.children = (total - np.repeat(before, self.counts)).astype(np.uint32)


def shared_parents(a: Block, b: Block, minsup: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Numbers of a child of a and of a child of b, and how many parents they share, where these are minsup or more."""
    at = pc.fill_null(pc.index_in(a.parents, value_set=b.parents), -1).to_numpy(zero_copy_only=False).astype(np.int64)
    parent = np.repeat(at, a.counts)
    child = a.children[parent >= 0]
    parent = parent[parent >= 0]
    order = np.argsort(child, kind="stable")
    child, parent = child[order].astype(np.int64), parent[order]
    begin, length = b.starts[parent], b.counts[parent]
    bounds = np.r_[0, np.flatnonzero(np.diff(child)) + 1, len(child)] if len(child) else np.zeros(1, np.int64)
    work = np.r_[0, np.cumsum(length)]
    many, most = len(b.names), max(1, (1 << 32) // max(1, len(b.names)) - 1)
    out = [[], [], []]
    k = 0
    while k < len(bounds) - 1:
        # As many whole children as fit, one at least.
        low = bounds[k]
        k2 = max(k + 1, int(np.searchsorted(work[bounds], work[low] + AT_ONCE, "right")) - 1)
        k2 = min(k2, k + most, len(bounds) - 1)
        high = bounds[k2]
        lens, total = length[low:high], int(work[high] - work[low])
        own = np.repeat(np.arange(k2 - k), np.diff(bounds[k : k2 + 1]))
        where = np.repeat((begin[low:high] - (work[low:high] - work[low])).astype(np.int32), lens)
        where += np.arange(total, dtype=np.int32)
        key = b.children[where]
        key += np.repeat((own * many).astype(np.uint32), lens)
        key.sort()
        hit = np.unique(key[minsup - 1 :][key[minsup - 1 :] == key[: max(0, total - minsup + 1)]])
        if len(hit):
            out[0].append(child[bounds[k + (hit // many).astype(np.int64)]])
            out[1].append((hit % many).astype(np.int64))
            out[2].append(np.searchsorted(key, hit, "right") - np.searchsorted(key, hit, "left"))
        k = k2
    return tuple(np.concatenate(x) if x else np.zeros(0, np.int64) for x in out)


def common_parents(g: Graph, minsup: int, blocks: int | None = None) -> DataFrame:
    """n1, n2, freq: both orders of every pair of nodes with minsup common parents or more, and each such node with itself.

    The edges are read twice (once counted), so a stored graph serves best."""
    many = blocks or max(LEAST_BLOCKS, -(-g.edges.count() // BLOCK_EDGES))
    kind = g.node_type

    def packed(edges: pa.Table) -> pa.Table:
        found = pack(edges, minsup)
        rows = [] if found is None else [(edges["block"][0].as_py(), *found)]
        kinds = (pa.int32(), *[pa.binary()] * 4)
        return pa.table([pa.array([r[k] for r in rows], t) for k, t in enumerate(kinds)], names=["block", "parents", "counts", "names", "steps"])

    def met(two: pa.Table) -> pa.Table:
        q, r = two["q"][0].as_py(), two["r"][0].as_py()
        block = {x["block"]: Block(x["parents"], x["counts"], x["names"], x["steps"]) for x in two.to_pylist()}
        # A block without children of enough parents has no row.
        left, right = block.get(q), block.get(r)
        if left is None or right is None:
            names = next(iter(block.values())).names
            a = b = names.slice(0, 0)
            freq = np.zeros(0, np.int64)
        else:
            x, y, freq = shared_parents(left, right, minsup)
            a, b = left.names.take(pa.array(x)), right.names.take(pa.array(y))
        if q != r:
            a, b, freq = pa.concat_arrays([a, b]), pa.concat_arrays([b, a]), np.r_[freq, freq]
        return pa.table([x.cast(pa.string()) if kind == "string" else x for x in (a, b)] + [pa.array(freq, pa.int64())], names=["n1", "n2", "freq"])

    dealt = g.edges.select("src", "dst", F.pmod(F.xxhash64("dst"), F.lit(many)).cast("int").alias("block"))
    once = dealt.groupBy("block").applyInArrow(packed, "block int, parents binary, counts binary, names binary, steps binary")
    other = F.explode(F.sequence(F.lit(0), F.lit(many - 1))).alias("other")
    twice = once.select("*", other).select(F.least("block", F.col("other").cast("int")).alias("q"), F.greatest("block", F.col("other").cast("int")).alias("r"), "block", "parents", "counts", "names", "steps")
    return twice.groupBy("q", "r").applyInArrow(met, f"n1 {kind}, n2 {kind}, freq bigint")
