"""Arrow kernels that work on a block of edges in memory."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa

#: Edges that a block kernel holds at a time, parts of a block that see the labels which the parts before them have
#: lowered, and hops that a part follows at most after all pointers of the block have been shortened.
BLOCK_EDGES, PARTS, HOPS = 1 << 20, 64, 64


class DisjointSets:
    """Union by smaller id, with path halving, over ids 0..n-1; of many pairs at once."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def find(self, x: np.ndarray) -> np.ndarray:
        up = self.up
        while True:
            parent = up[x]
            far = up[parent]
            if (far == parent).all():
                return parent
            up[x] = far

    def union(self, a: np.ndarray, b: np.ndarray) -> None:
        """Each root goes under the least root that a pair joins it to, until no pair joins two."""
        a, b = self.find(a), self.find(b)
        while len(apart := np.flatnonzero(a != b)):
            a, b = np.maximum(a[apart], b[apart]), np.minimum(a[apart], b[apart])
            np.minimum.at(self.up, a, b)
            a, b = self.find(a), self.find(b)  # the roots that went under others are all among a, so their paths are halved together

    def compress(self) -> np.ndarray:
        return self.find(np.arange(len(self.up)))


def block_minima(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ids in the block and the smallest id connected to each within it; the order of ids is that of their places."""
    ids, place = np.unique(np.concatenate([src, dst]), return_inverse=True)
    sets = DisjointSets(len(ids))
    sets.union(place[: len(src)], place[len(src) :])
    return ids, ids[sets.compress()]


def _rows(a, b, names=("id", "label")):
    return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=list(names))


def forest_kernel(limit: int):
    """Edges of a partition -> (id, smallest id reached). Edges are gathered until they are as many as the forest's, and then folded into it, so each is folded in about log(n) times; the forest holds each touched id once."""

    def run(batches):
        ids, least = np.zeros(0, np.int64), np.zeros(0, np.int64)
        held, size = [], 0

        def folded():
            got = block_minima(np.concatenate([ids, *(a for a, _ in held)]), np.concatenate([least, *(b for _, b in held)]))
            if len(got[0]) > limit:
                raise ValueError(f"over {limit} ids meet in one task; use order2, which needs no such task")
            return got

        for batch in batches:
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            size += batch.num_rows
            if size >= max(BLOCK_EDGES, len(ids)):
                ids, least = folded()
                held, size = [], 0
        if held:
            ids, least = folded()
        if len(ids):
            yield _rows(ids, least)

    return run


def min_map(labels: np.ndarray, a: np.ndarray, b: np.ndarray, order: int) -> None:
    """Min-mapping of an order by the edges a-b in place: the smaller of the labels order hops away goes to both chains up to there."""
    chains = [a, b]
    x, y = labels[a], labels[b]
    for _ in range(min(order, HOPS) - 1):
        further = labels[x], labels[y]
        chains += [x, y]
        if (further[0] == x).all() and (further[1] == y).all():
            break
        x, y = further
    least = np.minimum(x, y)
    np.minimum.at(labels, np.concatenate(chains), np.tile(least, len(chains)))


def sweep(labels: np.ndarray, a: np.ndarray, b: np.ndarray, order: int) -> None:
    """One pass over the edges of a block, part by part, each seeing what the parts before it have lowered."""
    for _ in range(max(order.bit_length() - 2, 0)):  # of orders over two, pointers are first followed over powers of two
        far = labels[labels]
        if (far == labels).all():
            break
        labels[:] = far
    wide = max(16, -(-len(a) // PARTS))
    for k in range(0, len(a), wide):
        min_map(labels, a[k : k + wide], b[k : k + wide], order)


def swept(a: np.ndarray, b: np.ndarray, labels: np.ndarray, order: int, sweeps: int) -> int:
    """Sweeps of a block's edges, at most as many as given (0: until no edge joins two labels); how many there were."""
    n = 0
    while not n or (n != sweeps and (labels[a] != labels[b]).any()):
        sweep(labels, a, b, order)
        n += 1
    return n


def thinning_kernel(order: int, sweeps: int, limit: int = BLOCK_EDGES):
    """Edges of a partition, block by block -> (id, down): an edge from each id to the smaller one that its label became, and those between labels that the sweeps left, each once; and a row without down for each id that some row is down to. They connect what the block's edges connect."""

    def block(held):
        src, dst = (np.concatenate(x) for x in zip(*held))
        ids, place = np.unique(np.concatenate([src, dst]), return_inverse=True)
        a, b = place[: len(src)], place[len(src) :]
        labels = np.arange(len(ids))
        swept(a, b, labels, order, sweeps)
        x, y = labels[a], labels[b]
        left = x != y
        pairs = np.unique(np.maximum(x[left], y[left]) * len(ids) + np.minimum(x[left], y[left]))
        low = np.flatnonzero(labels < np.arange(len(ids)))
        loops = np.unique(src[src == dst])
        one, two = np.concatenate([low, pairs // len(ids)]), np.concatenate([labels[low], pairs % len(ids)])
        below = np.unique(two)
        return pa.RecordBatch.from_arrays(
            [pa.array(np.concatenate([ids[one], loops, ids[below]]), pa.int64()), pa.concat_arrays([pa.array(np.concatenate([ids[two], loops]), pa.int64()), pa.nulls(len(below), pa.int64())])], names=["id", "down"]
        )

    def run(batches):
        held, size = [], 0
        for batch in batches:
            for at in range(0, batch.num_rows, limit):
                part = batch.slice(at, limit)
                held.append((part.column(0).to_numpy(), part.column(1).to_numpy()))
                size += part.num_rows
                if size >= limit:
                    yield block(held)
                    held, size = [], 0
        if size:
            yield block(held)

    return run


def round_of_order(labels: np.ndarray, src: np.ndarray, dst: np.ndarray, order: int) -> tuple[np.ndarray, int]:
    """Labels after a synchronous round of order 1 or 2 over directed edges, and the number of vertices that had a neighbour of a smaller label."""
    nearest = np.full_like(labels, len(labels))
    np.minimum.at(nearest, dst, labels[src])
    if order == 1:
        return np.minimum(labels, nearest), int((nearest < labels).sum())
    far = labels[labels]
    least = far.copy()  # of the vertex and its neighbours
    np.minimum.at(least, dst, far[src])
    out = np.minimum(labels, least)
    np.minimum.at(out, labels, least)
    return out, int((nearest < labels).sum())


def round_of_hooking(labels: np.ndarray, src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, int]:
    """Labels after hooking of parents and of ends, and compressing; all read the labels from before."""
    far = labels[labels]
    out = np.minimum(labels, far)
    np.minimum.at(out, labels[dst], far[src])
    np.minimum.at(out, dst, far[src])
    return out, 0


def pointers_kernel(doublings: int):
    """All pointers (id, label) of a forest, each id once, no label over its id -> the same with the labels followed so many times twice as far, or to the roots."""

    def run(batches):
        held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        if not held:
            return
        ids, label = (np.concatenate(x) for x in zip(*held))
        del held
        order = np.argsort(ids)
        ids, label = ids[order], label[order]
        after = np.minimum(np.searchsorted(ids, label), len(ids) - 1).astype(np.int32)
        goes_on = ids[after] == label
        at = np.arange(len(ids), dtype=np.int32)  # of the pointer whose label each has got to
        for _ in range(doublings):
            far = np.where(goes_on[at], at[after[at]], at)
            if (far == at).all():
                break
            at = far
        for k in range(0, len(ids), 1 << 18):
            yield _rows(ids[k : k + (1 << 18)], label[at[k : k + (1 << 18)]])

    return run


def followers_kernel(width: int):
    """Sorted rows of a partition, of so many columns and its number -> the columns of each row, those of the next one, the number and place null; and the first row with place 0 and the last one with place 1, without a next one."""

    def paired(own, after, place):
        n = own.num_rows
        columns = [own.column(k) for k in range(width)]
        following = [pa.nulls(n, c.type) for c in columns] if after is None else [after.column(k) for k in range(width)]
        return pa.RecordBatch.from_arrays([*columns, *following, own.column(width), pa.array([place] * n, pa.int32())], names=[f"c{k}" for k in range(2 * width + 2)])

    def run(batches):
        last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            if last is None:
                yield paired(batch.slice(0, 1), None, 0)
            else:
                yield paired(last, batch.slice(0, 1), None)
            if batch.num_rows > 1:
                yield paired(batch.slice(0, batch.num_rows - 1), batch.slice(1), None)
            last = batch.slice(batch.num_rows - 1)
        if last is not None:
            yield paired(last, None, 1)

    return run


def rounds_kernel(step, most: int, early: bool):
    """Canonical edges of a whole graph -> (id, label) of their ends after all rounds, and a row (k, changed, open, seconds) for each round, that which finds labels settled with k 0 if it does so early. step: labels, src, dst, k -> labels, open."""

    def run(batches):
        held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
        if not held:
            return
        ids, place = np.unique(np.concatenate([x for pair in zip(*held) for x in pair]), return_inverse=True)
        del held
        src = place.astype(np.int32)
        m = len(src) // 2
        dst, labels, rounds = np.concatenate([src[m:], src[:m]]), np.arange(len(ids), dtype=np.int32), []
        for k in range(1, most + 2):
            if k > most:
                raise ValueError(f"not done after {most} iterations")
            began = time.perf_counter()
            new, above = step(labels, src, dst, k)
            changed, labels = int((new < labels).sum()), new
            settled = early and not above
            rounds.append((0 if settled else k, changed, above, time.perf_counter() - began))
            if settled or (not early and not changed):
                break
        none = lambda n, kind: pa.nulls(n, kind)
        names, kinds = ["id", "label", "k", "changed", "open", "seconds"], (pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.float64())
        n = len(rounds)
        yield pa.RecordBatch.from_arrays([none(n, kinds[0]), none(n, kinds[1]), *(pa.array(list(c), t) for c, t in zip(zip(*rounds), kinds[2:]))], names=names)
        for at in range(0, len(ids), 1 << 18):
            own = ids[at : at + (1 << 18)]
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array(ids[labels[at : at + (1 << 18)]], pa.int64()), *(none(len(own), t) for t in kinds[2:])], names=names)

    return run


def similar_pairs(threshold: float, thin: bool):
    """Rows (i, j, b, id, v) of the blocks i and j -> (src, dst) of vectors of one length, of one block each, whose cosine is over the threshold; or only as many that connect what these connect. Products that are within rounding of the threshold are added up again one by one."""

    def pairs(ids, v, left, right, same):
        norm = np.sqrt(np.cumsum(v * v, axis=1)[:, -1])
        for at in range(0, len(left), 256):
            own = left[at : at + 256]
            dots, over = v[own] @ v[right].T, threshold * norm[own][:, None] * norm[right]
            found = dots > over
            for p, q in zip(*np.nonzero(np.abs(dots - over) <= 1e-12 * v.shape[1] * norm[own][:, None] * norm[right])):
                a, b = sorted((own[p], right[q]), key=lambda r: ids[r])
                found[p, q] = np.cumsum(v[a] * v[b])[-1] > threshold * norm[a] * norm[b]
            p, q = np.nonzero(found)
            a, b = ids[own[p]], ids[right[q]]
            kept = a < b if same else a != b
            yield np.minimum(a, b)[kept], np.maximum(a, b)[kept]

    def connecting(a, b):
        ids, place = np.unique(np.concatenate([a, b]), return_inverse=True)
        labels = np.arange(len(ids))
        swept(place[: len(a)], place[len(a) :], labels, 2, 0)
        low = np.flatnonzero(labels < np.arange(len(ids)))
        return ids[labels[low]], ids[low]

    def run(rows: pa.Table) -> pa.Table:
        ids, block = (rows.column(c).to_numpy() for c in ("id", "b"))
        i, j = rows.column("i")[0].as_py(), rows.column("j")[0].as_py()
        vectors = rows.column("v").combine_chunks()
        length = np.diff(vectors.offsets.to_numpy())
        flat, first = vectors.values.to_numpy(), vectors.offsets.to_numpy()[:-1]
        out, held = [], (np.zeros(0, np.int64), np.zeros(0, np.int64))
        for n in np.unique(length[length > 0]).tolist():
            same = np.flatnonzero(length == n)
            v = flat[first[same][:, None] + np.arange(n)]
            for a, b in pairs(ids[same], v, np.flatnonzero(block[same] == i), np.flatnonzero(block[same] == j), i == j):
                if thin:
                    held = connecting(np.concatenate([held[0], a]), np.concatenate([held[1], b]))
                else:
                    out.append(_rows(a, b, ("src", "dst")))
        return pa.Table.from_batches(out or [_rows(*held, ("src", "dst"))])

    return run


def cogrouped_kernel(order: int, sweeps: int):
    """A block's edges (block, src, dst) and its ends' rows (block, id, label, far) -> (id, label) that the sweeps lowered. An end's pointer, and its pointer's, are part of the block, as order 2 and more lower them too."""

    def run(edges: pa.Table, ends: pa.Table) -> pa.Table:
        src, dst = (edges.column(c).to_numpy() for c in ("src", "dst"))
        ids, label, far = (ends.column(c).to_numpy() for c in ("id", "label", "far"))
        known = np.unique(np.concatenate([ids, label, far]))
        labels = np.arange(len(known))
        labels[np.searchsorted(known, label)] = np.searchsorted(known, far)
        labels[np.searchsorted(known, ids)] = np.searchsorted(known, label)
        before = labels.copy()
        swept(np.searchsorted(known, src), np.searchsorted(known, dst), labels, order, sweeps)
        low = np.flatnonzero(labels < before)
        return pa.table({"id": known[low], "label": known[labels[low]]})

    return run
