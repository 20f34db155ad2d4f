"""Exact Jaccard self-join of shingle sets by T-occurrence search, to component ids.

1. Every text becomes its set of hashed word shingles; equal sets are one node from here on.
2. Nodes that may link are brought together. Sets of sizes a, b that reach the threshold differ in at most
   (a + b)(1 - t)/(1 + t) shingles. Per group of sizes, shingles are dealt to more cells than that, so some
   cells hold the same shingles in both, and more of them than either side may leave out: each node signs all
   but its D emptiest cells. Nodes with a common signature are compared by size and by counts of shingles
   per hash range, whose differences bound that of the sets from below; what may still link is an edge, and
   the components of the edges are clusters, outside of which no link exists.
3. Within a cluster, inverted lists over its nodes answer every node's T-occurrence query by DivideSkip:
   the L longest lists are set aside, the short ones merged through a heap with threshold T - L, and
   candidates binary-probed in the long lists. T is the overlap that the smallest partner in range needs;
   the exact test follows. Nodes known to be connected aren't probed again, as only components are asked for.
   A cluster too heavy for one task is cut by size: classes as wide as linked sets may differ, two neighbouring
   ones a window; a window still too heavy is cut to blocks, and every pair of its blocks is a task.
4. Components of the verified links give each document the smallest doc_id it reaches.

Edge cases: null or empty texts, or texts of white space, have no shingles and are components of their own; a
text with fewer words than a shingle is one shingle; a null doc_id is one more id, before all others, and as
component_id null; repeated rows are copies of each other; an empty table stays empty; columns other than
doc_id and text are ignored.
"""

from __future__ import annotations

import heapq
from array import array
from collections.abc import Iterator
from dataclasses import dataclass
from hashlib import blake2b

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from crowding.llm.common import claim, join_counted, keyed, partitions, release, released, settle, slices, table, unkey, utf8

#: Signatures a group of cells may bring to one task, and shingles a task of the search may hold.
SIGNED = 300_000
WEIGHT = 500_000
#: Signatures a task of the first step holds before it hands them on, nodes a task compares at a time, and cells of a comparison.
HELD = 250_000
COMPARED = 20_000
CELLS = 1_000_000
#: Rows of cluster members up to which they are broadcast to the texts.
BROADCAST_ROWS = 150_000
#: Bytes of words with their hashes that a worker keeps.
CACHE = 16 << 20
_M = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)]


class _Hashes(dict):
    held = 0

    def __missing__(self, word: bytes) -> int:
        h = xxhash.xxh3_64_intdigest(word)
        if len(word) < 64:
            self.held += 200 + len(word)
            if self.held > CACHE:
                self.forget()
            self[word] = h
        return h

    def forget(self) -> None:
        self.clear()
        self.held = 0


_hashes = _Hashes()


def _mix(z: np.ndarray) -> np.ndarray:
    z = (z ^ (z >> np.uint64(31))) * _M[0]
    return z ^ (z >> np.uint64(29))


def shingles(text: bytes, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word shingles."""
    claim("shingles", _hashes.forget)
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    if len(words) < width:
        return np.array([xxhash.xxh3_64_intdigest(b" ".join(words), seed=len(words))], np.uint64)
    ids = np.array(list(map(_hashes.__getitem__, words)), np.uint64)
    n = len(ids) - width + 1
    z = ids[:n].copy()
    for j in range(1, width):
        z = _mix(z) + ids[j : j + n]
    return np.unique(_mix(z))


@dataclass(frozen=True)
class Threshold:
    """Two sets link when den * intersection >= num * union."""

    num: int
    den: int

    def overlap(self, a, b):
        """Least intersection of linked sets of these sizes."""
        return -(-self.num * (a + b) // (self.num + self.den))

    def links(self, a, b, common):
        return self.den * common >= self.num * (a + b - common)

    def largest(self, a: int) -> int:
        return a * self.den // self.num

    def smallest(self, a: int) -> int:
        return -(-a * self.num // self.den)

    def groups(self, top: int) -> list[tuple[int, int, int]]:
        """(largest size, cells, cells left out) of the size groups up to top; the larger of two linked sets is in
        the smaller one's group or the next."""
        out, low = [], 1
        while not out or out[-1][0] < top or low <= self.largest(top) + 1:
            high = self.largest(low)
            differ = 2 * high * (self.den - self.num) // (self.den + self.num)
            spare = -(-(differ + 1) // 12) if differ else 0
            out.append((high, differ + 1 + 2 * spare if differ else 0, spare))
            low = high + 1
        return out


def node_id(s: np.ndarray) -> bytes:
    return blake2b(s.tobytes(), digest_size=16).digest()


def sketch(s: np.ndarray) -> bytes:
    """Counts of shingles by the top bits of their hashes, 255 at most; 64 of them, or more so that about 12 or
    fewer shingles share one, as differences of unrelated sets grow with the root of both."""
    bits = min(16, max(6, (len(s) // 12).bit_length()))
    return np.minimum(np.bincount((s >> np.uint64(64 - bits)).astype(np.int64), minlength=1 << bits), 255).astype(np.uint8).tobytes()


def stacked(sketches: list[bytes], width: int) -> np.ndarray:
    """Rows of width counts; longer sketches are folded, which can only lessen differences."""
    out = np.empty((len(sketches), width), np.int32)
    for i, x in enumerate(sketches):
        a = np.frombuffer(x, np.uint8)
        out[i] = a if len(a) == width else a.reshape(width, -1).sum(axis=1)
    return out


def profiles(docs: DataFrame, width: int) -> DataFrame:
    """key, n_shingles, set_id (null without shingles), sketch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = [shingles(t, width) for t in utf8(b, "text")]
            yield pa.RecordBatch.from_arrays([b.column("key"), pa.array([len(s) for s in sets], pa.int64()), pa.array([node_id(s) if len(s) else None for s in sets], pa.binary()), pa.array([sketch(s) for s in sets], pa.binary())], names=["key", "n_shingles", "set_id", "sketch"])

    return docs.mapInArrow(released(run), "key long, n_shingles long, set_id binary, sketch binary")


def signatures(sets: list[np.ndarray], limit: Threshold) -> np.ndarray:
    """Rows (signature, node) of all sets, as uint64."""
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    if not len(sizes) or not sizes.max():
        return np.zeros((0, 2), np.uint64)
    groups = limit.groups(int(sizes.max()))
    own = np.searchsorted([g[0] for g in groups], sizes)
    nodes = np.array([int.from_bytes(node_id(s)[:8], "little") for s in sets], dtype=np.uint64)
    out = []
    for step in (0, 1):
        g = own + step
        cells, spare = (np.array([x[k] for x in groups], dtype=np.int64)[g] for k in (1, 2))
        use = np.flatnonzero((cells > 0) & (sizes > 0))
        if not len(use):
            continue
        cells, spare, size = cells[use], spare[use], sizes[use]
        tokens = np.concatenate([sets[i] for i in use])
        doc = np.repeat(np.arange(len(use)), size)
        first = np.cumsum(cells) - cells
        cell = first[doc] + (_mix(tokens ^ _M[1]) % cells[doc].astype(np.uint64)).astype(np.int64)
        order = np.argsort(cell)
        at = cell[order]
        edge = np.flatnonzero(np.append(True, at[1:] != at[:-1]))
        total = np.zeros(int(cells.sum()), np.uint64)
        held = np.zeros(len(total), np.int64)
        total[at[edge]] = np.add.reduceat(_mix(tokens * _M[2])[order], edge)
        held[at[edge]] = np.diff(np.append(edge, len(at)))
        owner = np.repeat(np.arange(len(use)), cells)
        place = np.arange(len(total)) - first[owner]
        # the emptiest cells of each set are left out; ties by place
        rank = np.lexsort((place, held, owner))
        left = np.empty(len(total), bool)
        left[rank] = place < spare[owner]  # ranks within an owner run 0, 1, ... as places do
        keep = np.flatnonzero(~left)
        sign = _mix(total[keep] + _mix((g[use][owner[keep]] * 1_000_003 + place[keep]).astype(np.uint64)) + held[keep].astype(np.uint64) * _M[1])
        out.append(np.stack([sign, nodes[use][owner[keep]]], axis=1))
    return np.concatenate(out) if out else np.zeros((0, 2), np.uint64)


def shared(rows: np.ndarray) -> np.ndarray:
    """Distinct rows (signature, node) of signatures with several nodes, one signature for each set of nodes."""
    order = np.lexsort((rows[:, 1], rows[:, 0]))
    rows = rows[order]
    rows = rows[np.append(True, (rows[1:] != rows[:-1]).any(axis=1))]
    first = np.flatnonzero(np.append(True, rows[1:, 0] != rows[:-1, 0]))
    size = np.diff(np.append(first, len(rows)))
    several = np.repeat(size > 1, size)
    rows, size = rows[several], size[size > 1]
    if not len(rows):
        return rows
    start = np.cumsum(size) - size
    who = np.add.reduceat(_mix(rows[:, 1] ^ _M[2]), start)  # 64 bits for a set of nodes
    _, one = np.unique(who + size.astype(np.uint64) * _M[0], return_index=True)
    keep = np.zeros(len(size), bool)
    keep[one] = True
    return rows[np.repeat(keep, size)]


def near_pairs(n: np.ndarray, sketches: list[bytes], limit: Threshold) -> np.ndarray:
    """Places (i, j) that connect what size and sketch do not tell apart.

    Each place reached looks at those not reached yet, so a group of near copies takes one look at each of them, not
    one at every pair.
    """
    sk = stacked(sketches, min(map(len, sketches)))
    far, out = np.arange(len(n)), []
    while len(far):
        queue, far = [int(far[0])], far[1:]
        while queue and len(far):
            i = queue.pop()
            hit = np.zeros(len(far), bool)
            for at in np.array_split(np.arange(len(far)), 1 + sk.shape[1] * len(far) // CELLS):
                j = far[at]
                small, large = np.minimum(n[i], n[j]), np.maximum(n[i], n[j])
                gap = np.abs(sk[j] - sk[i]).sum(axis=1)
                hit[at] = (large <= small * limit.den // limit.num) & (gap <= (small + large) * (limit.den - limit.num) // (limit.den + limit.num))
            found = far[hit]
            out += [(i, j) for j in found.tolist()]
            queue += found.tolist()
            far = far[~hit]
    return np.array(out, np.int64).reshape(-1, 2)


def spanning(pairs: np.ndarray) -> np.ndarray:
    """Of rows (a, b) as many as connect what all of them connect: fewer than there are nodes."""
    nodes, at = np.unique(pairs, return_inverse=True)
    forest = Forest(len(nodes))
    keep = [forest.join(i, j) for i, j in at.reshape(-1, 2).tolist()]
    return pairs[np.array(keep, dtype=bool)]


def candidate_edges(groups: DataFrame, nodes: DataFrame, limit: Threshold) -> DataFrame:
    """(a, b) that connect nodes with a common signature that may link, a task's as a forest, as only components are asked
    for; groups: sign, node; nodes: node, n, sketch.

    A task goes through its signatures in order, holds some of them at a time and a forest of what it has handed on. There
    are no more tasks for more texts: each would tell anew how the members of one group of copies are connected."""

    def check(sign: np.ndarray, node: np.ndarray, n: np.ndarray, sk: list[bytes]) -> np.ndarray:
        first = np.flatnonzero(np.append(True, sign[1:] != sign[:-1]))
        size = np.diff(np.append(first, len(sign)))
        two = first[size == 2]
        small, large = np.minimum(n[two], n[two + 1]), np.maximum(n[two], n[two + 1])
        gap, width = np.zeros(len(two), np.int64), np.array([min(len(sk[i]), len(sk[i + 1])) for i in two], dtype=np.int64)
        for w in np.unique(width).tolist():
            for at in np.array_split(np.flatnonzero(width == w), 1 + w * len(two) // CELLS):
                gap[at] = np.abs(stacked([sk[i] for i in two[at]], w) - stacked([sk[i + 1] for i in two[at]], w)).sum(axis=1)
        ok = (gap <= (small + large) * (limit.den - limit.num) // (limit.den + limit.num)) & (large <= small * limit.den // limit.num)
        out = [np.stack([node[two[ok]], node[two[ok] + 1]], axis=1)]
        for f, m in zip(first[size > 2].tolist(), size[size > 2].tolist()):
            out.append(node[f : f + m][near_pairs(n[f : f + m], sk[f : f + m], limit)])
        pairs = np.concatenate(out)
        return spanning(np.unique(np.sort(pairs[pairs[:, 0] != pairs[:, 1]], axis=1), axis=0))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows, told = [], 0, Told()

        def flush(ended: bool) -> pa.RecordBatch:
            """Of whole signatures; the last one may go on in the next batch."""
            nonlocal held, rows
            t = pa.Table.from_batches(held).combine_chunks()
            sign = t.column("sign").to_numpy()
            stop = len(sign) if ended else int(np.searchsorted(sign, sign[-1]))
            held, rows = t.slice(stop).to_batches(), len(sign) - stop
            t = t.slice(0, stop)
            pairs = check(sign[:stop], t.column("node").to_numpy(), t.column("n").to_numpy(), t.column("sketch").to_pylist())
            pairs = pairs[np.array([told.join(a, b) for a, b in pairs.tolist()], dtype=bool)]
            return pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])

        for b in slices(batches, COMPARED):
            if b.num_rows:
                held.append(b)
                rows += b.num_rows
            if rows >= COMPARED and b.column("sign")[-1] != held[0].column("sign")[0]:
                yield flush(False)
        if rows:
            yield flush(True)

    tasks = partitions(groups.sparkSession)
    dealt = groups.join(nodes, "node").select("sign", "node", "n", "sketch").repartitionById(tasks, F.pmod("sign", F.lit(tasks)).cast("int"))
    return dealt.sortWithinPartitions("sign").mapInArrow(released(run), "a long, b long")


def candidate_groups(docs: DataFrame, width: int, limit: Threshold, total: int) -> DataFrame:
    """(sign, node) of signatures that several nodes have; total is the number of shingles of all texts."""
    spread = (limit.den - limit.num) / (limit.den + limit.num)
    dests = max(partitions(docs.sparkSession), int(total * spread * 5 / SIGNED) + 1)

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0

        def flush():
            rows = np.unique(np.concatenate(held), axis=0)
            dest = (rows[:, 0] % np.uint64(dests)).astype(np.int64)
            order = np.argsort(dest, kind="stable")
            rows, dest = rows[order], dest[order]
            first = np.flatnonzero(np.append(True, dest[1:] != dest[:-1]))
            parts = [p.tobytes() for p in np.split(rows, first[1:])]
            return pa.RecordBatch.from_arrays([pa.array(dest[first]), pa.array(parts, pa.binary())], names=["dest", "rows"])

        for b in slices(batches):
            rows = signatures([shingles(t, width) for t in utf8(b, "text")], limit)
            if len(rows):
                held.append(rows)
                n += len(rows)
            if n > HELD:
                yield flush()
                held, n = [], 0
        if n:
            yield flush()

    def join(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = np.frombuffer(b"".join(pdf["rows"]), np.uint64).reshape(-1, 2)
        rows = shared(rows).astype(np.int64)
        release()
        return pd.DataFrame({"sign": rows[:, 0], "node": rows[:, 1]})

    return docs.mapInArrow(released(sign), "dest long, rows binary").groupBy("dest").applyInPandas(join, "sign long, node long")


def components(edges: DataFrame, name: str = "components") -> DataFrame:
    """(node, root): the smallest node each node of the edges reaches, itself included.

    Alternating stars: a node hands its larger neighbours to the smallest one, then its smaller ones; the
    edges settle as stars around roots. Each round is written to the shared folder.
    """
    now = settle(edges.filter("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), name)
    size = now.count()
    while True:
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"), F.count(F.lit(1)).alias("n"))
        large = join_counted(both, low, "a", 2 * size).filter("b > a and b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        root = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(root, "a").select(F.explode(F.array("a", "b")).alias("a"), F.col("m").alias("b")).filter("a <> b").distinct()
        after = settle(small, name)
        same = [x.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(20,0)")), F.lit(0))).first() for x in (now, after)]
        now, size = after, same[1][0]
        if same[0] == same[1]:
            break
    roots = now.select(F.col("b").alias("node")).distinct().withColumn("root", F.col("node"))
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(roots)


def t_occurrence(lists: list[np.ndarray], t: int, skip=None) -> list[tuple[int, int]]:
    """(id, occurrences) of the ids in at least t of the sorted lists, by DivideSkip.

    skip: tells of an array of candidates which need no answer.
    """
    if t <= 0:
        raise ValueError("t must be positive")
    lists = sorted((x for x in lists if len(x)), key=len)
    if len(lists) < t:
        return []
    aside = min(t - 1, int(t / (0.0085 * np.log2(len(lists[-1]) + 1) + 1)))
    short, long = lists[: len(lists) - aside], lists[len(lists) - aside :]
    ids, counts, last = array("q"), array("q"), None
    for x in heapq.merge(*[s.tolist() for s in short]):
        if x == last:
            counts[-1] += 1
        else:
            ids.append(x)
            counts.append(1)
            last = x
    cand, seen = np.frombuffer(ids, np.int64), np.frombuffer(counts, np.int64)
    keep = seen >= t - aside
    cand, seen = cand[keep], seen[keep]
    if skip is not None and len(cand):
        open_ = ~skip(cand)
        cand, seen = cand[open_], seen[open_]
    for left, x in zip(range(aside, 0, -1), reversed(long)):
        if not len(cand):
            break
        at = np.minimum(np.searchsorted(x, cand), len(x) - 1)
        seen = seen + (x[at] == cand)
        keep = seen + left - 1 >= t
        cand, seen = cand[keep], seen[keep]
    return list(zip(cand.tolist(), seen.tolist()))


class Forest:
    def __init__(self, n: int):
        self.up = list(range(n))
        self.trees = n

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> bool:
        i, j = self.find(i), self.find(j)
        if i == j:
            return False
        self.up[max(i, j)] = min(i, j)
        self.trees -= 1
        return True


class Told:
    """A forest of node ids, forgotten when it has HELD of them: what comes then is told once more."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def join(self, i: int, j: int) -> bool:
        if len(self.up) > HELD:
            self.up.clear()
        i, j = self._root(i), self._root(j)
        self.up[max(i, j)] = min(i, j)
        return i != j

    def _root(self, i: int) -> int:
        up = self.up
        while (j := up.setdefault(i, i)) != i:
            up[i] = up[j]
            i = j
        return i


def link_cluster(sets: list[np.ndarray], limit: Threshold) -> list[tuple[int, int]]:
    """Links that connect what the sets' links connect (places in the list), found by T-occurrence queries."""
    order = sorted(range(len(sets)), key=lambda i: len(sets[i]))
    sizes = np.array([len(sets[i]) for i in order], dtype=np.int64)
    owner = np.repeat(np.arange(len(order)), sizes)
    flat, token = np.unique(np.concatenate([sets[i] for i in order]), return_inverse=True)
    by = np.argsort(token, kind="stable")
    edge = np.append(np.searchsorted(token[by], np.arange(len(flat))), len(token))
    postings = owner[by]
    first = np.append(0, np.cumsum(sizes))
    forest, out = Forest(len(order)), []
    for q in range(len(order) - 1):
        if forest.trees == 1:
            break
        size = int(sizes[q])
        stop = int(np.searchsorted(sizes, limit.largest(size), side="right"))  # partners are q + 1 .. stop - 1
        if stop <= q + 1:
            continue
        lists = []
        for k in token[first[q] : first[q + 1]].tolist():
            p = postings[edge[k] : edge[k + 1]]
            if len(p) > 1:
                a, b = p.searchsorted(q + 1), p.searchsorted(stop)
                if b > a:
                    lists.append(p[a:b])
        t = int(limit.overlap(size, size))
        mine = forest.find(q)
        for c, common in t_occurrence(lists, t, lambda ids: np.array([forest.find(i) == mine for i in ids.tolist()], dtype=bool)):
            if limit.links(size, int(sizes[c]), common) and forest.join(q, c):
                out.append((order[q], order[c]))
    return out


def verified_links(docs: DataFrame, members: DataFrame, width: int, limit: Threshold) -> DataFrame:
    """(a, b) keys of documents, one a distinct set, whose links connect the clusters' nodes.

    members: key, set_id, n_shingles, cluster.
    """
    spark = docs.sparkSession
    weight = members.groupBy(F.col("cluster").alias("c")).agg(F.sum("n_shingles").alias("weight"))
    total = weight.agg(F.coalesce(F.sum("weight"), F.lit(0))).first()[0]
    tasks = max(partitions(spark), int(total / WEIGHT * 4) + 1)
    known = members.join(weight, F.col("cluster") == F.col("c")).select("key", "set_id", "n_shingles", "cluster", "weight")
    light = known.filter(F.col("weight") <= WEIGHT).select("key", "set_id", "cluster", F.pmod(F.xxhash64("cluster"), F.lit(tasks)).alias("task"))
    size_class = F.floor(F.log(F.col("n_shingles").cast("double")) / F.log(F.lit(limit.den / limit.num)) + F.lit(1e-9))
    heavy = known.filter(F.col("weight") > WEIGHT).withColumn("class", size_class)
    heavy = heavy.withColumn("window", F.explode(F.array(F.col("class"), F.col("class") - 1)))
    windows = heavy.groupBy(F.col("cluster").alias("c"), F.col("window").alias("w")).agg(F.ceil(F.sum("n_shingles") / F.lit(WEIGHT)).cast("int").alias("blocks"))
    heavy = heavy.join(windows, (F.col("cluster") == F.col("c")) & (F.col("window") == F.col("w"))).withColumn("block", F.pmod(F.xxhash64("set_id"), F.col("blocks")).cast("int"))
    heavy = heavy.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    place = F.xxhash64("cluster", "window", F.least("block", "other"), F.greatest("block", "other")).bitwiseAND(F.lit(2**62 - 1)) + F.lit(tasks)
    dealt = settle(light.unionByName(heavy.select("key", "set_id", "cluster", place.alias("task"))), "join-tasks")
    if dealt.count() <= BROADCAST_ROWS:
        rows = docs.join(F.broadcast(dealt), "key")
    else:
        rows = docs.join(dealt, "key")

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        found = []
        for _, part in pdf.groupby("cluster", sort=True):
            sets, keys, seen = [], [], set()
            for key, want, text in zip(part["key"], part["set_id"], part["text"]):
                s = shingles(text.encode(), width)
                if want not in seen and node_id(s) == bytes(want):  # rows that share an id may have other texts
                    seen.add(want)
                    sets.append(s)
                    keys.append(key)
            if len(sets) > 1:
                found += [(keys[x], keys[y]) for x, y in link_cluster(sets, limit)]
        release()
        return pd.DataFrame(found, columns=["a", "b"]).astype("int64")

    return rows.select("task", "cluster", "key", "set_id", "text").groupBy("task").applyInPandas(search, "a long, b long")


def join_components(docs: DataFrame, width: int, num: int, den: int) -> DataFrame:
    """key, n_shingles, set_id, component (a key) of every row; docs: key, text."""
    limit = Threshold(num, den)
    prof = settle(profiles(docs, width), "join-profiles")
    total = prof.agg(F.coalesce(F.sum("n_shingles"), F.lit(0))).first()[0]
    reps = prof.filter("n_shingles > 0").groupBy("set_id").agg(F.min("key").alias("rep"), F.first("n_shingles").alias("n"), F.first("sketch").alias("sketch"))
    node = F.expr("cast(conv(concat_ws('', transform(sequence(7, 0, -1), i -> substring(hex(set_id), 2 * i + 1, 2))), 16, -10) as long)")
    nodes = settle(reps.withColumn("node", node), "join-nodes")
    groups = settle(candidate_groups(docs, width, limit, total), "join-groups")
    clusters = components(candidate_edges(groups, nodes.select("node", "n", "sketch"), limit), "join-clusters")
    members = nodes.join(clusters, "node").select(F.col("rep").alias("key"), "set_id", F.col("n").alias("n_shingles"), F.col("root").alias("cluster"))
    links = components(verified_links(docs, members, width, limit), "join-links")
    label = nodes.drop("node").join(links, F.col("rep") == F.col("node"), "left").select(F.col("set_id").alias("of"), F.coalesce("root", "rep").alias("root"))
    return prof.join(label, F.col("set_id") == F.col("of"), "left").select("key", "n_shingles", "set_id", F.coalesce("root", "key").alias("component"))


def keep_one(docs: DataFrame, width: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """docs with one row of each component, its smallest doc_id; rows without shingles all stay.

    Of rows that repeat that id with the same shingles, one stays. What goes is listed by id and set; few such
    rows are broadcast, more are joined by shuffle.
    """
    from pyspark.sql import Window as W
    from pyspark.sql import types as T

    got = settle(join_components(keyed(docs), width, num, den), "join-result").filter("n_shingles > 0")
    out = got.filter("key <> component").select(F.col("key").alias("dd__k"), F.col("set_id").alias("dd__s")).distinct()
    repeats = got.filter("key = component").groupBy("key", "set_id").count().filter("count > 1").limit(1).count()
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in slices(batches):
            sets = [shingles((t or "").encode(), width) for t in b.column(at).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([node_id(s) if len(s) else None for s in sets], pa.binary())], names=[*b.schema.names, "dd__set"])

    few = out.count() <= BROADCAST_ROWS
    rows = docs.withColumn("dd__key", F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63))))
    ids_twice = rows.groupBy("dd__key").count().filter("count > 1").limit(1).count()
    if not ids_twice:  # an id is a row: no need to look at sets again
        gone = out.select("dd__k")
        return rows.join(F.broadcast(gone) if few else gone, F.col("dd__key") == F.col("dd__k"), "left_anti").select(*docs.columns)
    rows = rows.mapInArrow(released(run), T.StructType([*rows.schema.fields, T.StructField("dd__set", T.BinaryType())]))
    rows = rows.join(F.broadcast(out) if few else out, (F.col("dd__key") == F.col("dd__k")) & (F.col("dd__set") == F.col("dd__s")), "left_anti")
    if repeats:
        n = F.row_number().over(W.partitionBy("dd__set", "dd__key").orderBy("dd__key"))
        rows = rows.withColumn("dd__n", F.when(F.col("dd__set").isNotNull(), n)).filter("dd__n = 1 or dd__set is null")
    return rows.select(*docs.columns)


def op7_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of all documents under 3-word shingles and Jaccard 0.9."""
    got = join_components(keyed(table(spark, sf_dir, "documents")), 3, 90, 100)
    return got.select(unkey().alias("doc_id"), "n_shingles", unkey("component").alias("component_id"))


SQL = r"""
WITH w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
             ELSE list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) END) AS sh FROM w),
u AS (SELECT doc_id, len(sh) AS n, unnest(sh) AS t FROM s),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, any_value(a.n) AS nx, any_value(b.n) AS ny, count(*) AS c
      FROM u a JOIN u b ON a.t = b.t AND a.doc_id <> b.doc_id AND 10 * a.n >= 9 * b.n AND 10 * b.n >= 9 * a.n GROUP BY 1, 2),
e AS (SELECT x, y FROM p WHERE 100 * c >= 90 * (nx + ny - c)),
r AS (WITH RECURSIVE walk(x, y) AS (SELECT x, y FROM e UNION SELECT walk.x, e.y FROM walk JOIN e ON walk.y = e.x) SELECT x, min(y) AS m FROM walk GROUP BY x)
SELECT s.doc_id, len(sh) AS n_shingles, least(s.doc_id, coalesce(r.m, s.doc_id)) AS component_id FROM s LEFT JOIN r ON r.x = s.doc_id
"""
