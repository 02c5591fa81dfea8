"""Approximate nearest neighbours: a neighbour graph by NN-descent, searched greedily.

Distinct vectors are the nodes (equal vectors are one node, so a vector that a third of all rows share is no hot spot). Nodes
are dealt to blocks of near vectors by a tree of hyperplanes, each near the widest direction of what it splits and at its
median; the tree is fitted on at most 32,768 nodes drawn by hash, every node is dealt, and a crowded leaf is dealt on by hash.
Most neighbours of a node are then in few blocks, so few vectors are sent. A block is one row of arrays, and everything that
blocks tell each other is a row addressed to a block, so a step of the algorithm is one Spark ``groupBy(block)``:

* seeding: nodes meet in their block, and once more in the leaf of a second tree with other hyperplanes, and keep their nearest
  of both; groups are of some thousand nodes: a bounded number of comparisons a node;
* each round of NN-descent joins neighbours of neighbours. A block sends its edges, with the vectors at their sources, to the
  blocks of their targets; those draw reverse neighbours and send back the vectors that were asked for; then each node
  compares its neighbours pairwise, new ones with all, and whatever improves a list goes to the block of its owner. Rounds
  go on until few lists change;
* search: a query starts from its own neighbours. Each round it opens the best nodes that it has not opened yet; their
  neighbours are compared in their own blocks, which answer with the similarity and, where that is promising, with the
  node's neighbours; nodes of the beam that came without are asked again. A search ends when all of its best ``beam`` nodes are open.

Lists and beams are of fixed length, as the method has it; rounds and steps are not (a graph or search that doesn't settle
is an error), and the recall against brute force is measured in the tests and the README. The scores of what was found are cosines of the
original vectors in double precision.

Edge cases: vectors that are null, zero, hold null or non-finite components, or have another length than most, take no part;
rows without an id neither; of repeated rows one counts; fewer than k candidates give fewer rows; an empty table gives an
empty result. Other columns are never looked at.
"""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from lincompress.llm.common import materialise, read, remove

EVERY, TOP = 50, 5
NEIGHBOURS, REVERSE, ENOUGH = 32, 32, 0.01
BLOCK, BEAM, WIDTH = 4096, 256, 64
#: Nodes that the trees are fitted on, and the fewest of them in a leaf; bits of a node's number inside its block.
SAMPLE, LEAF, INSIDE = 32_768, 32, 24
#: Rounds and steps after which something is wrong.
MOST_ROUNDS, MOST_STEPS = 60, 200
MESSAGE = "block int, kind int, size long, a binary, b binary, c binary, d binary, e binary"
STATE, EDGES, REVERSED, REPLY, UPDATE, QUERY, ASK, ANSWER = range(8)
NONE = -(1 << 63)


def _block(ids: np.ndarray) -> np.ndarray:
    return ids >> INSIDE


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        x = a.view(np.uint64) * np.uint64(0xD1342543DE82EF95) + b.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        return (x ^ (x >> np.uint64(29))) * np.uint64(0x94D049BB133111EB)


class Post:
    """Rows to send."""

    def __init__(self):
        self.rows: list[tuple] = []

    def send(self, block: int, kind: int, *parts: np.ndarray) -> None:
        self.rows.append((int(block), kind, len(parts[0]), *[np.ascontiguousarray(x).tobytes() for x in parts], *[b""] * (5 - len(parts))))

    def table(self) -> pa.Table:
        kinds = [pa.int32(), pa.int32(), pa.int64(), *[pa.binary()] * 5]
        columns = list(zip(*self.rows, strict=True)) or [()] * 8
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=[x.split()[0] for x in MESSAGE.split(", ")])


def _read(table: pa.Table) -> dict[int, list[dict]]:
    out: dict[int, list[dict]] = {}
    for r in table.to_pylist():
        out.setdefault(r["kind"], []).append(r)
    return out


class State:
    """A block's nodes: ids (sorted), unit vectors, and K neighbours each with similarity and whether they are new."""

    def __init__(self, ids, vectors, near, sims, new):
        self.ids, self.vectors, self.near, self.sims, self.new = ids, vectors, near, sims, new

    @classmethod
    def of(cls, row: dict, dim: int) -> State:
        ids = np.frombuffer(row["a"], np.int64)
        n = len(ids)
        return cls(ids, np.frombuffer(row["b"], np.float32).reshape(n, dim), *(np.frombuffer(row[x], t).reshape(n, -1) for x, t in (("c", np.int64), ("d", np.float32), ("e", np.uint8))))

    def send(self, post: Post, block: int) -> None:
        post.send(block, STATE, self.ids, self.vectors, self.near, self.sims, self.new)

    def merge(self, owner: np.ndarray, cand: np.ndarray, sim: np.ndarray) -> int:
        """Puts candidates into the lists; returns how many entered."""
        n, k = self.near.shape
        place = np.searchsorted(self.ids, owner)
        rows = np.concatenate([np.repeat(np.arange(n), k), place])
        ids = np.concatenate([self.near.ravel(), cand])
        sims = np.concatenate([self.sims.ravel(), sim])
        new = np.concatenate([self.new.ravel(), np.ones(len(cand), np.uint8)])
        keep = ids != NONE
        rows, ids, sims, new = rows[keep], ids[keep], sims[keep], new[keep]
        order = np.lexsort((new, ids, rows))
        rows, ids, sims, new = rows[order], ids[order], sims[order], new[order]
        first = np.r_[True, (rows[1:] != rows[:-1]) | (ids[1:] != ids[:-1])] if len(rows) else np.zeros(0, bool)
        rows, ids, sims, new = rows[first], ids[first], sims[first], new[first]
        order = np.lexsort((-sims, rows))
        rows, ids, sims, new = rows[order], ids[order], sims[order], new[order]
        rank = np.arange(len(rows)) - np.searchsorted(rows, rows)
        top = rank < k
        before = int(self.new.sum())
        self.near, self.sims, self.new = np.full((n, k), NONE), np.full((n, k), -2.0, np.float32), np.zeros((n, k), np.uint8)
        at = rows[top], rank[top]
        self.near[at], self.sims[at], self.new[at] = ids[top], sims[top], new[top]
        return int(self.new.sum()) - before


class Tree:
    """A binary tree of hyperplanes, each at the median of the sample's part that it splits; steps: how far a random direction is turned to the widest."""

    def __init__(self, x: np.ndarray, depth: int, steps: int, seed: int):
        rng, self.depth = np.random.default_rng(seed), depth
        self.planes, self.cuts = np.zeros(((1 << depth) - 1, x.shape[1]), np.float32), np.zeros((1 << depth) - 1, np.float32)
        parts = [x]
        for level in range(depth):
            halves = []
            for i, part in enumerate(parts):
                plane, centred = rng.normal(size=x.shape[1]), part - part.mean(axis=0) if len(part) else part
                for _ in range(steps if len(part) else 0):
                    turned = centred.T @ (centred @ plane)
                    size = np.sqrt(turned @ turned)
                    if size > 0:
                        plane = turned / size
                along = part @ plane.astype(np.float32)
                cut = np.median(along) if len(part) else 0.0
                at = (1 << level) - 1 + i
                self.planes[at], self.cuts[at] = plane, cut
                halves += [part[along <= cut], part[along > cut]]
            parts = halves

    def leaf(self, x: np.ndarray) -> np.ndarray:
        at = np.zeros(len(x), np.int64)
        for level in range(self.depth):
            plane = at + (1 << level) - 1
            at = 2 * at + (np.einsum("ij,ij->i", x, self.planes[plane]) > self.cuts[plane])
        return at


def _matrix(column, dim: int) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return np.asarray(column.flatten(), np.float32).reshape(-1, dim)


def deal(vectors: DataFrame, count: int, dim: int) -> tuple[DataFrame, int]:
    """key, node (its number: block and place in it), other (leaf of the second tree), and the number of blocks; vectors: key (a hash, distinct), vector (array of float, unit length)."""
    depth = 0
    while count > BLOCK << depth and LEAF << depth < SAMPLE:
        depth += 1
    parts = 1 << 20
    drawn = vectors if count <= SAMPLE else vectors.where(F.pmod(F.xxhash64("key"), F.lit(parts)) < SAMPLE * parts // count)
    sample = _matrix(drawn.select("vector").toArrow()["vector"], dim) if depth else np.zeros((0, dim), np.float32)
    trees = [Tree(sample, depth, steps, seed) for seed, steps in enumerate((8, 1))]

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _matrix(batch.column(1), dim)
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(tree.leaf(x)) for tree in trees]], names=["key", "leaf", "other"])

    dealt = materialise(vectors.select("key", "vector").mapInArrow(each, "key long, leaf long, other long"), "leaves")
    held = {r.leaf: r["count"] for r in dealt.groupBy("leaf").count().collect()}  # a row for each leaf, at most SAMPLE / LEAF
    shares = [max(1, -(-held.get(i, 0) // BLOCK)) if held.get(i, 0) > 2 * BLOCK else 1 for i in range(1 << depth)]
    start = np.cumsum([0, *shares])
    table = lambda v: F.element_at(F.lit([int(k) for k in v]), (F.col("leaf") + 1).cast("int"))
    block = table(start[:-1]).cast("long") + F.pmod(F.xxhash64("key", F.lit(1)), table(shares).cast("long"))
    place = F.row_number().over(Window.partitionBy("block").orderBy("key"))
    numbered = dealt.withColumn("block", block).withColumn("node", F.shiftleft("block", INSIDE) + place)
    return materialise(numbered.select("key", "node", "other"), "numbers"), int(start[-1])


def _seed(nodes: DataFrame, k: int, dim: int) -> DataFrame:
    """Blocks with the nearest of two groups of nodes: their own block, and the leaf of the second tree. A crowded group is cut by lot."""
    second = 1 << 50

    def group(table: pa.Table) -> pa.Table:
        ids, x, seed = table["node"].to_numpy(), _matrix(table["vector"], dim), table["seed"][0].as_py()
        post = Post()
        owners, cands, sims = [], [], []
        lot = np.argsort(_mix(ids, np.full(1, seed, np.int64)), kind="stable")
        for mine in np.array_split(lot, -(-len(lot) // (2 * BLOCK))):
            m = min(k, len(mine) - 1)
            for a in range(0, len(mine) if m > 0 else 0, 512):
                own = mine[a : a + 512]
                s = x[own] @ x[mine].T
                s[np.arange(len(own)), a + np.arange(len(own))] = -2
                top = np.argpartition(-s, m - 1, axis=1)[:, :m]
                owners.append(np.repeat(ids[own], m))
                cands.append(ids[mine[top]].ravel())
                sims.append(np.take_along_axis(s, top, 1).ravel())
        owner, cand, sim = (np.concatenate(v) if v else np.zeros(0, t) for v, t in ((owners, np.int64), (cands, np.int64), (sims, np.float32)))
        if seed < second:  # the block itself: its nodes come along
            post.send(seed, UPDATE, owner, cand, sim.astype(np.float32), ids, x)
            return post.table()
        to = _block(owner)
        order = np.argsort(to, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(to[order])) + 1) if len(to) else ():
            post.send(to[part[0]], UPDATE, owner[part], cand[part], sim[part].astype(np.float32))
        return post.table()

    def settle(table: pa.Table) -> pa.Table:
        rows, post = _read(table)[UPDATE], Post()
        ids = np.concatenate([np.frombuffer(r["d"], np.int64) for r in rows])
        x = np.concatenate([np.frombuffer(r["e"], np.float32).reshape(-1, dim) for r in rows])
        order = np.argsort(ids)
        n = len(ids)
        state = State(ids[order], x[order], np.full((n, k), NONE), np.full((n, k), -2.0, np.float32), np.zeros((n, k), np.uint8))
        state.merge(*(np.concatenate([np.frombuffer(r[c], t) for r in rows]) for c, t in (("a", np.int64), ("b", np.int64), ("c", np.float32))))
        state.send(post, table["block"][0].as_py())
        return post.table()

    dealt = nodes.select("node", "vector", F.explode(F.array(F.shiftright("node", INSIDE), F.col("other") + F.lit(second))).alias("seed"))
    return dealt.groupBy("seed").applyInArrow(group, MESSAGE).groupBy("block").applyInArrow(settle, MESSAGE)


def _tell(state: State, block: int, post: Post) -> None:
    """Edges to the blocks of their targets, with the vectors and bounds at their sources."""
    src = np.repeat(np.arange(len(state.ids)), state.near.shape[1])
    dst, new = state.near.ravel(), state.new.ravel()
    keep = dst != NONE
    src, dst, new = src[keep], dst[keep], new[keep]
    to = _block(dst)
    order = np.argsort(to, kind="stable")
    for part in np.split(order, np.flatnonzero(np.diff(to[order])) + 1) if len(to) else ():
        b = to[part[0]]
        own, at = np.unique(src[part], return_inverse=True)
        header = np.concatenate([[block, len(own)], state.ids[own]]).astype(np.int64)
        body = np.column_stack([state.vectors[own], state.sims[own, -1:]]).astype(np.float16)
        post.send(b, EDGES, header, at.astype(np.int32), dst[part], new[part], body)


def _draw(table: pa.Table, dim: int, reverse: int, salt: int) -> pa.Table:
    """In the block of the targets: draw reverse neighbours, answer the senders."""
    rows, post, block = _read(table), Post(), table["block"][0].as_py()
    for r in rows[STATE]:
        state = State.of(r, dim)
        state.send(post, block)
        ends, starts, new, names, bodies = [], [], [], [], []
        for e in rows.get(EDGES, []):
            header = np.frombuffer(e["a"], np.int64)
            at, dst = np.frombuffer(e["b"], np.int32), np.frombuffer(e["c"], np.int64)
            own = header[2:]
            starts.append(own[at])
            ends.append(dst)
            new.append(np.frombuffer(e["d"], np.uint8))
            names.append(own)
            bodies.append(np.frombuffer(e["e"], np.float16).reshape(len(own), dim + 1))
            asked = np.unique(dst)
            mine = np.searchsorted(state.ids, asked)
            post.send(header[0], REPLY, asked, np.column_stack([state.vectors[mine], state.sims[mine, -1:]]).astype(np.float16))
        if ends:
            end, start, fresh = np.concatenate(ends), np.concatenate(starts), np.concatenate(new)
            order = np.lexsort((_mix(start ^ np.int64(salt), end), end))
            end, start, fresh = end[order], start[order], fresh[order]
            take = np.arange(len(end)) - np.searchsorted(end, end) < reverse
            end, start, fresh = end[take], start[take], fresh[take]
            used = np.unique(start)
            name, body = np.concatenate(names), np.concatenate(bodies)
            name, first = np.unique(name, return_index=True)
            post.send(block, REVERSED, end, start, fresh, used, body[first][np.searchsorted(name, used)])
    return post.table()


def _members(state: State, rows: dict, dim: int, reverse: int):
    """Each node's neighbours both ways (ids, new), and names, vectors and bounds of all that occur."""
    names, bodies = [state.ids], [np.column_stack([state.vectors, state.sims[:, -1:]]).astype(np.float16)]
    n = len(state.ids)
    back, back_new = np.full((n, reverse), NONE), np.zeros((n, reverse), np.uint8)
    for r in rows.get(REVERSED, []):
        end, start, fresh = np.frombuffer(r["a"], np.int64), np.frombuffer(r["b"], np.int64), np.frombuffer(r["c"], np.uint8)
        at = np.searchsorted(state.ids, end), np.arange(len(end)) - np.searchsorted(end, end)
        back[at], back_new[at] = start, fresh
        names.append(np.frombuffer(r["d"], np.int64))
        bodies.append(np.frombuffer(r["e"], np.float16).reshape(-1, dim + 1))
    for r in rows.get(REPLY, []):
        names.append(np.frombuffer(r["a"], np.int64))
        bodies.append(np.frombuffer(r["b"], np.float16).reshape(-1, dim + 1))
    name, first = np.unique(np.concatenate(names), return_index=True)
    body = np.concatenate(bodies)[first].astype(np.float32)
    return np.concatenate([state.near, back], 1), np.concatenate([state.new, back_new], 1), name, body[:, :-1], body[:, -1]


def _join(table: pa.Table, dim: int, reverse: int) -> pa.Table:
    """Neighbours of neighbours: pairs among each node's neighbours, sent to whose lists they improve."""
    rows, post, block = _read(table), Post(), table["block"][0].as_py()
    for r in rows.get(STATE, []):
        state = State.of(r, dim)
        ids, new, name, x, bound = _members(state, rows, dim, reverse)
        k = state.near.shape[1]
        # sources and candidates as places in name
        at = np.searchsorted(name, ids).clip(0, len(name) - 1)
        there = (ids != NONE) & (name[at] == ids)
        found = []
        for a in range(0, len(ids), 128):
            p, ok, fresh = at[a : a + 128], there[a : a + 128], new[a : a + 128] > 0
            v = x[p]
            s = v @ v.transpose(0, 2, 1)
            good = ok[:, :, None] & ok[:, None, :] & (fresh[:, :, None] | fresh[:, None, :]) & (s > bound[p][:, :, None]) & (p[:, :, None] != p[:, None, :])
            c, i, j = np.nonzero(good)
            found.append((p[c, i], p[c, j], s[c, i, j]))
        owner, cand, sim = (np.concatenate(v) for v in zip(*found, strict=True))
        _, first = np.unique(owner.astype(np.int64) * len(name) + cand, return_index=True)
        owner, cand, sim = owner[first], cand[first], sim[first]
        order = np.lexsort((-sim, owner))
        owner, cand, sim = owner[order], cand[order], sim[order]
        best = np.arange(len(owner)) - np.searchsorted(owner, owner) < k
        owner, cand, sim = name[owner[best]], name[cand[best]], sim[best]
        state.new = np.zeros_like(state.new)
        state.send(post, block)
        to = _block(owner)
        for b in np.unique(to):
            part = to == b
            post.send(b, UPDATE, owner[part], cand[part], sim[part])
    return post.table()


def _accept(table: pa.Table, dim: int) -> tuple[State | None, int]:
    rows = _read(table)
    if STATE not in rows:
        return None, 0
    state, entered = State.of(rows[STATE][0], dim), 0
    if UPDATE in rows:
        entered = state.merge(*(np.concatenate([np.frombuffer(r[c], t) for r in rows[UPDATE]]) for c, t in (("a", np.int64), ("b", np.int64), ("c", np.float32))))
    return state, entered


def _tidy(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of rounds that are over."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def build(nodes: DataFrame, count: int, dim: int, k: int = NEIGHBOURS, reverse: int = REVERSE, enough: float = ENOUGH) -> DataFrame:
    """The graph as block rows with the drawn reverse neighbours beside them; nodes: node, other, vector (array of float, unit length)."""

    def tell(table: pa.Table) -> pa.Table:
        state, entered = _accept(table, dim)
        post = Post()
        if state is not None:
            state.send(post, table["block"][0].as_py())
            _tell(state, table["block"][0].as_py(), post)
        return post.table()

    def step(salt: int):
        return lambda table: _draw(table, dim, reverse, salt)

    now = materialise(_seed(nodes, k, dim), "graph")
    for turn in range(MOST_ROUNDS):
        drawn = now.groupBy("block").applyInArrow(tell, MESSAGE).groupBy("block").applyInArrow(step(turn * 7919 + 1), MESSAGE)
        old, now = now, materialise(drawn.groupBy("block").applyInArrow(lambda t: _join(t, dim, reverse), MESSAGE), "graph")
        remove(old)
        _tidy(nodes.sparkSession)
        offered = now.where(F.col("kind") == UPDATE).agg(F.sum("size")).first()[0] or 0
        if offered <= enough * count * k:
            break
    else:
        raise RuntimeError("the neighbour graph did not settle")

    def finish(table: pa.Table) -> pa.Table:
        rows = _read(table)
        post, block = Post(), table["block"][0].as_py()
        for r in rows.get(STATE, []):
            state = State.of(r, dim)
            ids, *_ = _members(state, {REVERSED: rows.get(REVERSED, [])}, dim, reverse)
            ids = np.sort(ids, axis=1)
            ids[:, 1:][ids[:, 1:] == ids[:, :-1]] = NONE
            post.send(block, STATE, state.ids, state.vectors, np.sort(ids, axis=1)[:, ::-1])
        return post.table()

    last = now.groupBy("block").applyInArrow(tell, MESSAGE).groupBy("block").applyInArrow(step(0), MESSAGE)
    return materialise(last.groupBy("block").applyInArrow(finish, MESSAGE), "index")


class Search:
    """The searches of the queries at home in one block. Per query: vector, opened nodes, beam (ids, similarities, neighbours)."""

    def __init__(self, state: list[dict]):
        self.queries = state

    @classmethod
    def load(cls, rows: list[dict]) -> Search:
        import pickle

        return cls([q for r in rows for q in pickle.loads(r["a"])])

    def send(self, post: Post, block: int) -> None:
        import pickle

        post.rows.append((block, QUERY, sum(not q["over"] for q in self.queries), pickle.dumps(self.queries, 5), *[b""] * 4))

    def hear(self, answers: list[dict]) -> None:
        by = {q["id"]: q for q in self.queries}
        width = None
        for r in answers:
            own, ids, sims, has, near = np.frombuffer(r["a"], np.int64), np.frombuffer(r["b"], np.int64), np.frombuffer(r["c"], np.float32), np.frombuffer(r["d"], np.int64), np.frombuffer(r["e"], np.int64)
            if len(has):
                width = len(near) // len(has)
                near = near.reshape(len(has), width)
            place = np.searchsorted(has, np.arange(len(own)))
            for x in np.unique(own):
                part = np.flatnonzero(own == x)
                with_near = part[np.isin(part, has)]
                by[x]["got"].append((ids[part], sims[part]))
                by[x]["near"].update({int(ids[i]): near[place[i]] for i in with_near})

    def open(self, beam: int, width: int) -> dict[int, np.ndarray]:
        """Query -> candidates to be compared next."""
        out = {}
        for q in self.queries:
            if q["over"]:
                continue
            ids, sims = (np.concatenate([q[c], *[g[k] for g in q["got"]]]) for k, c in ((0, "ids"), (1, "sims")))
            q["got"] = []
            ids, once = np.unique(ids, return_index=True)
            sims = sims[once]
            order = np.argsort(-sims, kind="stable")[:beam]
            q["ids"], q["sims"] = ids[order], sims[order]
            q["near"] = {i: q["near"][i] for i in q["ids"].tolist() if i in q["near"]}
            ready = [i for i in q["ids"].tolist() if i in q["near"] and i not in q["opened"]][:width]
            q["opened"].update(ready)
            cand = np.unique(np.concatenate([q["near"].pop(i) for i in ready])) if ready else np.zeros(0, np.int64)
            cand = cand[(cand != NONE) & ~np.isin(cand, q["seen"])]
            q["seen"] = np.union1d(q["seen"], cand)
            if q["near"]:  # what is seen need not be carried
                flat, seen = np.concatenate(list(q["near"].values())), q["seen"]
                keep = (flat != NONE) & (seen[np.searchsorted(seen, flat).clip(0, len(seen) - 1)] != flat)
                cuts = np.r_[0, np.cumsum(keep)][np.cumsum([0, *map(len, q["near"].values())])].tolist()
                flat = flat[keep]
                q["near"] = {i: flat[a:b].copy() for i, a, b in zip(q["near"], cuts[:-1], cuts[1:], strict=True)}
            if not len(cand):
                # what is left of the beam came without its neighbours
                cand = np.array([i for i in q["ids"].tolist() if i not in q["opened"] and i not in q["near"]][:width], np.int64)
            waits = any(i in q["near"] and i not in q["opened"] for i in q["ids"].tolist())
            q["over"] = not len(cand) and not waits
            if len(cand):
                out[q["id"]] = cand
        return out


def search(index: DataFrame, queries: DataFrame, dim: int, top: int, beam: int = BEAM, width: int = WIDTH) -> DataFrame:
    """(query, node) of the best nodes found for each query node, itself included; queries: node."""

    def begin(key, left: pa.Table, right: pa.Table) -> pa.Table:
        post, block = Post(), key[0].as_py()
        for r in _read(left).get(STATE, []):
            ids = np.frombuffer(r["a"], np.int64)
            x, near = np.frombuffer(r["b"], np.float32).reshape(-1, dim), np.frombuffer(r["c"], np.int64).reshape(len(ids), -1)
            found = []
            for q in np.unique(right["node"].to_numpy()):
                i = np.searchsorted(ids, q)
                found.append({"id": int(q), "x": x[i], "ids": np.array([q]), "sims": np.array([1.0], np.float32), "near": {int(q): near[i]}, "opened": set(), "seen": np.array([q]), "got": [], "over": False})
            own = Search(found)
            _ask(own, own.open(beam, width), block, post)
        return post.table()

    def _ask(own: Search, cands: dict[int, np.ndarray], block: int, post: Post) -> None:
        own.send(post, block)
        if not cands:
            return
        by = {q["id"]: q for q in own.queries}
        names = np.array(list(cands), np.int64)
        owner = np.repeat(np.arange(len(names)), [len(c) for c in cands.values()])
        cand = np.concatenate(list(cands.values()))
        x = np.stack([by[i]["x"] for i in cands])
        # what a node must reach for its neighbours to be of use
        bound = np.array([by[i]["sims"][-1] if len(by[i]["sims"]) >= beam else -2 for i in cands], np.float32)
        bound -= np.float32(1e-6)  # a node of the beam itself brings its neighbours
        to = _block(cand)
        for b in np.unique(to):
            part = np.flatnonzero(to == b)
            used, at = np.unique(owner[part], return_inverse=True)
            post.send(b, ASK, np.concatenate([[block, len(used)], names[used]]).astype(np.int64), at.astype(np.int32), cand[part], np.column_stack([x[used], bound[used]]).astype(np.float32))

    def answer(key, left: pa.Table, right: pa.Table) -> pa.Table:
        rows, post = _read(right), Post()
        for r in rows.get(QUERY, []):
            post.rows.append((r["block"], QUERY, r["size"], r["a"], *[b""] * 4))
        for s in _read(left).get(STATE, []):
            ids = np.frombuffer(s["a"], np.int64)
            x, near = np.frombuffer(s["b"], np.float32).reshape(-1, dim), np.frombuffer(s["c"], np.int64).reshape(len(ids), -1)
            for r in rows.get(ASK, []):
                header, at, cand = np.frombuffer(r["a"], np.int64), np.frombuffer(r["b"], np.int32), np.frombuffer(r["c"], np.int64)
                body = np.frombuffer(r["d"], np.float32).reshape(-1, dim + 1)
                place = np.searchsorted(ids, cand)
                sims = np.einsum("ij,ij->i", x[place], body[at, :-1])
                has = np.flatnonzero(sims > body[at, -1])
                # the best answers of each query bring their neighbours, as many as it can open at once
                order = has[np.lexsort((-sims[has], at[has]))]
                has = np.sort(order[np.arange(len(order)) - np.searchsorted(at[order], at[order]) < width])
                post.send(header[0], ANSWER, header[2:][at], cand, sims.astype(np.float32), has, near[place[has]])
        return post.table()

    def go_on(table: pa.Table) -> pa.Table:
        rows, post, block = _read(table), Post(), table["block"][0].as_py()
        if QUERY in rows:
            own = Search.load(rows[QUERY])
            own.hear(rows.get(ANSWER, []))
            _ask(own, own.open(beam, width), block, post)
        return post.table()

    at_home = queries.select("node", F.shiftright("node", INSIDE).cast("int").alias("block"))
    now = materialise(index.groupBy("block").cogroup(at_home.groupBy("block")).applyInArrow(begin, MESSAGE), "search")
    for turn in range(MOST_STEPS + 1):
        if not now.where((F.col("kind") == QUERY) & (F.col("size") > 0)).limit(1).count():
            break
        if turn == MOST_STEPS:
            raise RuntimeError("searches did not end")
        heard = index.groupBy("block").cogroup(now.groupBy("block")).applyInArrow(answer, MESSAGE)
        old, now = now, materialise(heard.groupBy("block").applyInArrow(go_on, MESSAGE), "search")
        remove(old)
        _tidy(index.sparkSession)

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                for q in Search.load([r]).queries:
                    order = np.argsort(-q["sims"], kind="stable")[:top]
                    yield pa.RecordBatch.from_arrays([pa.array([q["id"]] * len(order), pa.int64()), pa.array(q["ids"][order])], names=["query", "found"])

    return now.where(F.col("kind") == QUERY).mapInArrow(best, "query long, found long")


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id, embedding, node: rows that take part; node is a hash of the vector."""
    e = F.col("embedding")
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), e.cast("array<double>").alias("embedding")).where("vec_id is not null and embedding is not null")
    fine = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    rows = rows.where(F.coalesce(fine, F.lit(False)))
    return rows.withColumn("embedding", F.transform("embedding", lambda x: x + F.lit(0.0))).withColumn("node", F.xxhash64("embedding"))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = TOP, **options) -> DataFrame:
    """query_id, rank, vec_id, score of the k nearest found; vectors: vec_id, embedding; queries: vec_id of rows of vectors."""
    spark = vectors.sparkSession
    schema = "query_id long, rank int, vec_id long, score double"
    rows = usable(vectors)
    sizes = rows.groupBy(F.size("embedding").alias("n")).count().orderBy(F.desc("count"), "n").first()
    if sizes is None:
        return spark.createDataFrame([], schema)
    dim = sizes["n"]
    rows = materialise(rows.where(F.size("embedding") == dim).dropDuplicates(["vec_id", "node"]), "vectors")
    first = Window.partitionBy("node").orderBy("vec_id")
    members = materialise(rows.select("vec_id", "node").withColumn("place", F.row_number().over(first)).where(F.col("place") <= k + 1), "members")
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x * x))
    leaders = rows.join(members.where("place = 1").select("vec_id", "node"), ["vec_id", "node"])
    vector = F.transform("embedding", lambda x: (x / F.col("norm")).cast("float"))
    given = materialise(leaders.withColumn("norm", norm).select(F.col("node").alias("key"), "embedding", vector.alias("vector")), "nodes")
    count = given.count()
    numbers, _ = deal(given.select("key", "vector"), count, dim)
    nodes = given.join(numbers, "key")
    number = numbers.select(F.col("key").alias("node"), F.col("node").alias("number"))
    members = members.join(number, "node").select("vec_id", F.col("number").alias("node"))
    asked = rows.select("vec_id", "node").join(queries.select(F.col("vec_id").cast("long").alias("vec_id")).distinct(), "vec_id").join(number, "node")
    asked = materialise(asked.select(F.col("vec_id").alias("query_id"), F.col("number").alias("query")), "asked")
    index = build(nodes.select("node", "other", "vector"), count, dim)
    found = search(index, asked.select(F.col("query").alias("node")).distinct(), dim, 4 * (k + 1), **options)

    def cosine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = (np.array(batch.column(i).to_pylist(), float).reshape(-1, dim) for i in (2, 3))
            score = (a * b).sum(axis=1) / (np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score)], names=["query", "found", "score"])

    vector = nodes.select("node", "embedding")
    pairs = found.join(vector.select(F.col("node").alias("found"), F.col("embedding").alias("b")), "found").join(vector.select(F.col("node").alias("query"), F.col("embedding").alias("a")), "query")
    scored = pairs.select("query", "found", "a", "b").mapInArrow(cosine, "query long, found long, score double")
    every = asked.join(scored, "query").join(members.select(F.col("node").alias("found"), "vec_id"), "found").where("vec_id <> query_id")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return every.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def op3_nn_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = read(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return nearest(vectors, vectors.where(F.col("vec_id") % EVERY == 0))
