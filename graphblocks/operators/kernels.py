"""numpy kernels for graphs that fit one task: the same steps as the DataFrame plans, and the searches that need a queue."""

from __future__ import annotations

import heapq
import math
from collections import deque

import numpy as np

from ..functions.hashes import mix_np, tabular_hash_np
from ..model import Csr

def border(csr: Csr, block: np.ndarray) -> np.ndarray:
    """The vertices with a neighbour in another block, ascending; flags, as a sort of all arcs costs more."""
    rows = csr.rows()
    flag = np.zeros(csr.n, bool)
    flag[rows[block[rows] != block[csr.nbr]]] = True
    return np.flatnonzero(flag)


# -- label propagation ---------------------------------------------------------


def packets(csr: Csr, active: np.ndarray, bound: int, sub_rounds: int, seed: int) -> np.ndarray:
    """Sub-round of each vertex, -1 if it isn't active."""
    out = np.full(csr.n, -1)
    who = np.flatnonzero(active)
    if not len(who):
        return out
    d = csr.degrees()[who]
    order = np.lexsort((csr.ids[who], mix_np(csr.ids[who], seed), d))
    before = np.cumsum(d[order]) - d[order]
    packet = before // bound
    out[who[order]] = packet * sub_rounds // (packet[-1] + 1) if len(packet) else 0
    return out


def strongest(csr: Csr, labels: np.ndarray, active: np.ndarray, weight: np.ndarray, bound: int, seed: int, label_ids: np.ndarray, stay_on_tie: bool = True):
    """Proposals (vertex, target, gain); labels index ``label_ids``, whose values make the ties."""
    keep = active[csr.rows()]
    src, to, w = csr.rows()[keep], labels[csr.nbr[keep]], csr.w[keep]
    if not len(src):
        z = np.zeros(0, np.int64)
        return z, z, z
    key = src * len(label_ids) + to
    uniq, inv = np.unique(key, return_inverse=True)
    s = np.bincount(inv, w).astype(np.int64)
    v, t = uniq // len(label_ids), uniq % len(label_ids)
    own = labels[v] == t
    stay = np.zeros(csr.n, np.int64)
    stay[v[own]] = s[own]
    ok = ~own & (weight[t] + csr.vw[v] <= bound)
    v, t, s = v[ok], t[ok], s[ok]
    tie = mix_np(label_ids[t], seed)
    order = np.lexsort((label_ids[t], tie, s, v))
    last = np.ones(len(order), bool)
    last[:-1] = v[order][1:] != v[order][:-1]
    best = order[last]
    v, t, s, tie = v[best], t[best], s[best], tie[best]
    want = s > stay[v]
    if not stay_on_tie:
        want |= (s == stay[v]) & (tie > mix_np(label_ids[labels[v]], seed))
    return v[want], t[want], s[want] - stay[v[want]]


def admit(csr: Csr, v: np.ndarray, t: np.ndarray, gain: np.ndarray, weight: np.ndarray, bound: int, seed: int, ranges: int = 0) -> np.ndarray:
    """Indices of the proposals that fit, as the DataFrame admission has them."""
    if not len(v):
        return np.zeros(0, np.int64)
    part = mix_np(csr.ids[v], 3) % ranges if ranges else np.zeros(len(v), np.int64)
    order = np.lexsort((csr.ids[v], mix_np(csr.ids[v], seed), -gain, part, t))
    w = csr.vw[v[order]]
    total = np.cumsum(w)
    key = t[order] * max(ranges, 1) + part[order]
    first = np.ones(len(order), bool)
    first[1:] = key[1:] != key[:-1]
    base = (total - w)[first][np.cumsum(first) - 1]
    room = bound - weight[t[order]]
    if ranges:
        room = room // ranges
    return order[total - base <= room]


def sclp(csr: Csr, bound: int, rounds: int, sub_rounds: int, seed: int, start: np.ndarray | None = None, n_labels: int | None = None, packet: int | None = None, stay_on_tie: bool = True, ranges: int = 0, keep_best: bool = False) -> np.ndarray:
    """Label propagation by sub-rounds; equals the DataFrame rounds.  With ``start``, labels are blocks 0 .. n_labels - 1."""
    labels = np.arange(csr.n) if start is None else start.astype(np.int64).copy()
    label_ids = csr.ids if start is None else np.arange(n_labels, dtype=np.int64)
    weight = np.bincount(labels, csr.vw, len(label_ids)).astype(np.int64)
    packet = packet or max(1000, int((len(csr.nbr) // 2) ** 0.5))
    active = np.ones(csr.n, bool)
    best, best_cut = labels.copy(), csr.cut(labels) if keep_best else 0
    for r in range(rounds):
        group = packets(csr, active, packet, sub_rounds, seed + r)
        moved = np.zeros(csr.n, bool)
        for s in range(sub_rounds):
            seed_r = seed + 1000 * r + s
            v, t, gain = strongest(csr, labels, group == s, weight, bound, seed_r, label_ids, stay_on_tie)
            take = admit(csr, v, t, gain, weight, bound, seed_r, ranges)
            v, t = v[take], t[take]
            np.subtract.at(weight, labels[v], csr.vw[v])
            np.add.at(weight, t, csr.vw[v])
            labels[v] = t
            moved[v] = True
        if keep_best and (now := csr.cut(labels)) < best_cut:
            best, best_cut = labels.copy(), now
        if not moved.any():
            break
        active = np.zeros(csr.n, bool)
        active[csr.nbr[moved[csr.rows()]]] = True
    return best if keep_best else labels


def sclp_sequential(csr: Csr, bound: int, rounds: int, seed: int, start: np.ndarray | None = None, n_labels: int | None = None) -> np.ndarray:
    """Label propagation with immediate effect, vertices by increasing degree: the sequential semantics."""
    rng = np.random.default_rng(seed)
    labels = (np.arange(csr.n) if start is None else start).astype(np.int64).tolist()
    weight = np.bincount(labels, csr.vw, n_labels or csr.n).astype(np.int64).tolist()
    ptr, nbr, w, vw = csr.indptr.tolist(), csr.nbr.tolist(), csr.w.tolist(), csr.vw.tolist()
    queue = np.lexsort((rng.random(csr.n), csr.degrees())).tolist()
    for _ in range(rounds):
        again: dict[int, None] = {}
        for v in queue:
            strength: dict[int, int] = {}
            for a in range(ptr[v], ptr[v + 1]):
                t = labels[nbr[a]]
                strength[t] = strength.get(t, 0) + w[a]
            own = labels[v]
            top, best = strength.get(own, 0), own
            for t, s in strength.items():
                if t != own and s >= top and weight[t] + vw[v] <= bound and (s > top or rng.random() < 0.5):
                    top, best = s, t
            if best != own:
                weight[own] -= vw[v]
                weight[best] += vw[v]
                labels[v] = best
                again.update(dict.fromkeys(nbr[ptr[v] : ptr[v + 1]]))
        if not again:
            break
        queue = list(again)
    return np.array(labels)


def matching(csr: Csr, bound: int, rounds: int, seed: int, two_hop: bool = False) -> np.ndarray:
    """Handshake matching; the label of a pair is its smaller vertex."""
    label = np.arange(csr.n)
    free = np.ones(csr.n, bool)
    src = csr.rows()
    fits = csr.vw[src] + csr.vw[csr.nbr] <= bound
    for r in range(rounds):
        arc = np.flatnonzero(free[src] & free[csr.nbr] & fits)
        if not len(arc):
            break
        a, b = src[arc], csr.nbr[arc]
        tie = mix_np(mix_np(csr.ids[a], seed + r) + mix_np(csr.ids[b], seed + r), seed + r)
        order = np.lexsort((np.maximum(a, b), np.minimum(a, b), tie, csr.w[arc], a))
        last = np.ones(len(order), bool)
        last[:-1] = a[order][1:] != a[order][:-1]
        choice = np.full(csr.n, -1)
        choice[a[order[last]]] = b[order[last]]
        v = np.flatnonzero((choice >= 0) & (np.arange(csr.n) < choice))
        v = v[choice[choice[v]] == v]
        if not len(v) and r:
            break
        label[choice[v]] = v
        free[v] = free[choice[v]] = False
    if two_hop:
        hub: dict[int, int] = {}
        for v in np.flatnonzero(free).tolist():
            a, b = csr.indptr[v], csr.indptr[v + 1]
            if a < b:
                h = int(csr.nbr[a + int(np.argmax(csr.w[a:b]))])
                o = hub.pop(h, None)
                if o is None:
                    hub[h] = v
                elif csr.vw[o] + csr.vw[v] <= bound:
                    label[v] = o
    return label


def pack_lone(csr: Csr, labels: np.ndarray, bound: int) -> np.ndarray:
    """Vertices without an edge gathered into clusters of at most ``bound``."""
    out, fill, name = labels.copy(), 0, -1
    for v in np.flatnonzero(csr.degrees() == 0).tolist():
        if name < 0 or fill + csr.vw[v] > bound:
            name, fill = v, 0
        out[v] = name
        fill += int(csr.vw[v])
    return out


def contract(csr: Csr, labels: np.ndarray) -> tuple[Csr, np.ndarray]:
    """The coarse graph and each vertex's place in it."""
    names, to = np.unique(labels, return_inverse=True)
    n = len(names)
    a, b = to[csr.rows()], to[csr.nbr]
    keep = a != b
    key, inv = np.unique(a[keep] * n + b[keep], return_inverse=True)
    w = np.bincount(inv, csr.w[keep], len(key)).astype(np.int64) if len(key) else np.zeros(0, np.int64)
    return Csr(np.arange(n, dtype=np.int64), np.searchsorted(key // n, np.arange(n + 1)), key % n, w, np.bincount(to, csr.vw, n).astype(np.int64)), to


# -- bisection and k-way starts ------------------------------------------------


#: From so many vertices on a side grows by arrays; below, lists take less time.
GROW_BY_ARRAYS = 1000
_GROW_BITS = 8
#: After so many vertices without an outer neighbour, those that follow are looked for together.
_GROW_IDLE = 16


def _without_outer(csr: Csr, out: np.ndarray, who: np.ndarray) -> np.ndarray:
    """Whether no neighbour of each vertex may still join."""
    size = csr.indptr[who + 1] - csr.indptr[who]
    ends = np.cumsum(size)
    arcs = np.arange(int(size.sum())) + np.repeat(csr.indptr[who] - (ends - size), size)
    seen = np.concatenate([[0], np.cumsum(out[csr.nbr[arcs]])])
    return seen[ends] == seen[ends - size]


# Steps that run often are short functions of their own: a traced run looks up the line of every object it makes, from the function's start.


def _take_least(key: np.ndarray, low: np.ndarray) -> int:
    """The vertex of the least key, which is taken out; -1 if there is none."""
    part = int(low.argmin())
    first = part << _GROW_BITS
    keys = key[first : first + (1 << _GROW_BITS)]
    at = int(keys.argmin())
    if keys[at] == np.inf:
        return -1
    keys[at] = np.inf
    low[part] = np.minimum.reduce(keys)
    return first + at


def _reach_for(near: np.ndarray, weight: np.ndarray, out: np.ndarray, tied: np.ndarray, key: np.ndarray, low: np.ndarray, rng: np.random.Generator) -> bool:
    """Whether a vertex with these arcs has outer neighbours; they get their ties and keys."""
    free = out[near]
    near = near[free]
    if not len(near):
        return False
    tied[near] += weight[free]
    keys = np.minimum(key[near], rng.random(len(near)) - tied[near])
    key[near] = keys
    np.minimum.at(low, near >> _GROW_BITS, keys)
    return True


def _grow_by_arrays(csr: Csr, target: int, cap_left: int, cap_right: int, rng: np.random.Generator) -> np.ndarray:
    """The side that :func:`_grow` makes, from the same draws, without an object for each arc, which a traced run pays for.

    Vertices in reach have a key, their draw less their tie, that only falls; the least key of each 256 vertices is kept.
    Draws for equal ties count with what bits the tie leaves of them.  Vertices without an outer neighbour change no key,
    so a run of them joins at once.
    """
    side, tied, key = np.ones(csr.n, np.int64), np.zeros(csr.n, np.int64), np.full(csr.n, np.inf)
    low = np.full((csr.n >> _GROW_BITS) + 1, np.inf)
    out = np.ones(csr.n, bool)
    ptr, nbr, w, vw = csr.indptr.tolist(), csr.nbr, csr.w, csr.vw.tolist()
    fill, total = 0, int(csr.vw.sum())
    order = iter(rng.permutation(csr.n).tolist())
    idle, patience, reach = 0, _GROW_IDLE, False
    while fill < target:
        if reach and idle >= patience:
            idle = 0
            who = np.flatnonzero(key < np.inf)
            who = who[np.argsort(key[who], kind="stable")]
            before = np.cumsum(csr.vw[who]) - csr.vw[who] + fill
            stops = ~_without_outer(csr, out, who) | (before >= target) | (before + csr.vw[who] > cap_left)
            who = who[: int(stops.argmax()) if stops.any() else len(who)]
            patience = _GROW_IDLE if len(who) > 100 else 2 * patience
            side[who], out[who], key[who] = 0, False, np.inf
            fill += int(csr.vw[who].sum())
            for part in np.unique(who >> _GROW_BITS).tolist():
                low[part] = np.minimum.reduce(key[part << _GROW_BITS : (part + 1) << _GROW_BITS])
            continue
        v = _take_least(key, low) if reach else -1
        if v < 0:
            reach = False
            v = next((u for u in order if side[u]), -1)
            if v < 0:
                break
        if fill + vw[v] > cap_left:
            if fill >= total - cap_right:
                break
            out[v] = False
            if (not reach or low.min() == np.inf) and (csr.vw[side == 1] + fill > cap_left).all():
                break
            continue
        side[v], out[v] = 0, False
        fill += vw[v]
        idle += 1
        a, b = ptr[v], ptr[v + 1]
        if a < b and _reach_for(nbr[a:b], w[a:b], out, tied, key, low, rng):
            idle, reach = 0, True
    return side


def _push_near(near: list[int], weight: list[int], side: list[int], tied: list[int], heap: list[tuple], rng: np.random.Generator) -> None:
    """The outer ones of these neighbours get their ties and entries."""
    free = [x for x, u in enumerate(near) if side[u] and tied[u] >= 0]
    for x, r in zip(free, rng.random(len(free)).tolist()):
        u = near[x]
        tied[u] += weight[x]
        heapq.heappush(heap, (-tied[u], r, u))


def _grow(csr: Csr, target: int, cap_left: int, cap_right: int, rng: np.random.Generator) -> np.ndarray:
    """0 for a side grown around a random vertex by most inner weight, 1 for the rest."""
    # Plain lists and ints: vertices come one at a time, and reading arrays item by item costs more than the step itself.
    vw, ptr, nbr, w = csr.vw.tolist(), csr.indptr.tolist(), csr.nbr.tolist(), csr.w.tolist()
    total = sum(vw)
    side, tied = [1] * csr.n, [0] * csr.n
    fill, heap = 0, []
    order = iter(rng.permutation(csr.n).tolist())
    while fill < target:
        v = -1
        while heap:
            s, _, u = heapq.heappop(heap)
            if side[u] and -s == tied[u]:
                v = u
                break
        if v < 0:
            v = next((u for u in order if side[u]), -1)
            if v < 0:
                break
        if fill + vw[v] > cap_left:
            if fill >= total - cap_right:
                break
            tied[v] = -1
            if not heap and all(vw[u] + fill > cap_left for u in range(csr.n) if side[u]):
                break
            continue
        side[v] = 0
        fill += vw[v]
        a, b = ptr[v], ptr[v + 1]
        _push_near(nbr[a:b], w[a:b], side, tied, heap, rng)
    return np.array(side, np.int64)


def bisect(csr: Csr, target: int, cap_left: int, cap_right: int, rng: np.random.Generator, starts: int = 4) -> np.ndarray:
    """0 and 1: a side grown around a random vertex by most inner weight, then two-way search; the best of some starts."""
    best, best_key = None, None
    grow = _grow_by_arrays if csr.n >= GROW_BY_ARRAYS else _grow
    for _ in range(max(1, starts)):
        side = fm(csr, grow(csr, target, cap_left, cap_right, rng), np.array([cap_left, cap_right]), rng)
        load = np.bincount(side, csr.vw, 2)
        key = (max(0, load[0] - cap_left) + max(0, load[1] - cap_right), csr.cut(side))
        if best_key is None or key < best_key:
            best, best_key = side, key
    return best


def recursive_bisect(csr: Csr, k: int, bound: int, rng: np.random.Generator, starts: int = 4) -> np.ndarray:
    """Blocks 0 .. k-1: two sides with ceil(k / 2) and floor(k / 2) blocks' share, then the same in each."""
    out = np.zeros(csr.n, np.int64)
    if k == 1 or csr.n == 0:
        return out
    left = -(-k // 2)
    total = int(csr.vw.sum())
    side = bisect(csr, total * left // k, left * bound, (k - left) * bound, rng, starts)
    for s, parts, base in ((0, left, 0), (1, k - left, left)):
        keep = side == s
        if keep.any():
            out[keep] = base + recursive_bisect(csr.subgraph(keep), parts, bound, rng, starts)
    return out


def _in_order(entries: tuple[np.ndarray, ...]) -> list[tuple]:
    """Entries of a queue (loss, draw, vertex, target, stamp) from the best on: one sort, where a heap of all would be taken apart one by one."""
    order = np.lexsort((entries[2], entries[1], entries[0]))
    return list(zip(*[c[order].tolist() for c in entries]))


def fm(csr: Csr, block: np.ndarray, caps: np.ndarray, rng: np.random.Generator, passes: int = 3, patience: int = 60) -> np.ndarray:
    """Search from all boundary vertices: best gain first, each vertex once a pass, back to the best state.

    Keeps the strength of every vertex to every block, so it is for small graphs.
    """
    k = len(caps)
    if k == 2:
        return _fm_two(csr, block, caps.tolist(), rng, passes, patience)
    block = block.copy()
    load = np.bincount(block, csr.vw, k).astype(np.int64)
    ptr, nbr, w, vw = csr.indptr, csr.nbr, csr.w, csr.vw
    rows, weight, limits = csr.rows(), vw.tolist(), caps.tolist()
    for _ in range(passes):
        ties = np.bincount(rows * k + block[nbr], w, csr.n * k).reshape(csr.n, k)
        heap: list[tuple] = []
        stamp = np.zeros(csr.n, np.int64)
        done = np.zeros(csr.n, bool)

        def entries(who: np.ndarray) -> tuple[np.ndarray, ...]:
            s = ties[who].copy()
            at = np.arange(len(who))
            stay = s[at, block[who]]
            s[load[None] + vw[who][:, None] > caps[None]] = -1
            s[at, block[who]] = -1
            t = s.argmax(1)
            top = s[at, t]
            stamp[who] += 1
            good = (top > 0) | ((top == 0) & (stay == 0))
            return (stay - top)[good], rng.random(int(good.sum())), who[good], t[good], stamp[who][good]

        def push(who: np.ndarray) -> None:
            for entry in zip(*[c.tolist() for c in entries(who)]):
                heapq.heappush(heap, entry)

        def push_one(v: int) -> None:
            # As push, by plain numbers: where blocks are full, most calls are for one vertex.
            own, x, top, t = int(block[v]), weight[v], -1.0, 0
            row = ties[v].tolist()
            for b, fill in enumerate(load.tolist()):
                if row[b] > top and b != own and fill + x <= limits[b]:
                    top, t = row[b], b
            stamp[v] += 1
            if top > 0 or (top == 0 and row[own] == 0):
                heapq.heappush(heap, (row[own] - top, rng.random(), v, t, int(stamp[v])))

        first, at = _in_order(entries(border(csr, block))), 0
        log, total, best, best_at = [], 0.0, 0.0, 0
        best_over = np.maximum(load - caps, 0).sum()
        while (heap or at < len(first)) and len(log) - best_at < patience:
            if at < len(first) and (not heap or first[at] < heap[0]):
                loss, _, v, t, st = first[at]
                at += 1
            else:
                loss, _, v, t, st = heapq.heappop(heap)
            if done[v] or st != stamp[v]:
                continue
            if load[t] + weight[v] > limits[t]:
                push_one(v)
                continue
            done[v] = True
            own = int(block[v])
            log.append((v, own))
            load[own] -= vw[v]
            load[t] += vw[v]
            block[v] = t
            total -= loss
            over = np.maximum(load - caps, 0).sum()
            if (over, -total) < (best_over, -best):
                best, best_over, best_at = total, over, len(log)
            near = nbr[ptr[v] : ptr[v + 1]]
            ties[near, own] -= w[ptr[v] : ptr[v + 1]]
            ties[near, t] += w[ptr[v] : ptr[v + 1]]
            near = near[~done[near]]
            if len(near):
                push(near)
        for v, b in reversed(log[best_at:]):
            load[block[v]] -= vw[v]
            load[b] += vw[v]
            block[v] = b
        if not best_at:
            break
    return block


def _fm_two(csr: Csr, block: np.ndarray, caps: list[int], rng: np.random.Generator, passes: int, patience: int) -> np.ndarray:
    """:func:`fm` of two blocks, with the same moves: the other block is the only target, so a step takes few array operations."""
    block = block.copy()
    load = np.bincount(block, csr.vw, 2).astype(np.int64).tolist()
    ptr, nbr, w, vw, weight = csr.indptr.tolist(), csr.nbr, csr.w.astype(np.float64), csr.vw, csr.vw.tolist()
    rows, nbr2 = csr.rows(), csr.nbr * 2
    for _ in range(passes):
        # The ties of v to block b are at 2 v + b.
        ties = np.bincount(rows * 2 + block[nbr], w, csr.n * 2)
        heap: list[tuple] = []
        stamp, done = np.zeros(csr.n, np.int64), np.zeros(csr.n, bool)

        def entries(who: np.ndarray) -> tuple[np.ndarray, ...]:
            own = block[who]
            at = who * 2 + own
            stay, top = ties[at], ties[at ^ 1]
            stamp[who] += 1
            room = np.array([caps[1] - load[1], caps[0] - load[0]])[own]
            good = np.flatnonzero((vw[who] <= room) & ((top > 0) | ((top == 0) & (stay == 0))))
            v = who[good]
            return (stay - top)[good], rng.random(len(good)), v, 1 - own[good], stamp[v]

        def push(who: np.ndarray) -> None:
            for entry in zip(*[c.tolist() for c in entries(who)]):
                heapq.heappush(heap, entry)

        def shift(arcs: slice, own: int, t: int) -> None:
            near, weights, ends = nbr[arcs], w[arcs], nbr2[arcs]
            ties[ends + own] -= weights
            ties[ends + t] += weights
            near = near[~done[near]]
            if len(near):
                push(near)

        first, at = _in_order(entries(border(csr, block))), 0
        log, total, best, best_at = [], 0.0, 0.0, 0
        best_over = max(load[0] - caps[0], 0) + max(load[1] - caps[1], 0)
        while (heap or at < len(first)) and len(log) - best_at < patience:
            if at < len(first) and (not heap or first[at] < heap[0]):
                loss, _, v, t, st = first[at]
                at += 1
            else:
                loss, _, v, t, st = heapq.heappop(heap)
            if done[v] or st != stamp[v]:
                continue
            if load[t] + weight[v] > caps[t]:
                stamp[v] += 1  # there is no other target
                continue
            done[v] = True
            own = 1 - t
            log.append((v, own))
            load[own] -= weight[v]
            load[t] += weight[v]
            block[v] = t
            total -= loss
            over = max(load[0] - caps[0], 0) + max(load[1] - caps[1], 0)
            if (over, -total) < (best_over, -best):
                best, best_over, best_at = total, over, len(log)
            shift(slice(ptr[v], ptr[v + 1]), own, t)
        for v, b in reversed(log[best_at:]):
            load[block[v]] -= weight[v]
            load[b] += weight[v]
            block[v] = b
        if not best_at:
            break
    return block


def swap_polish(csr: Csr, block: np.ndarray, k: int, bound: int, most: int = 400) -> np.ndarray:
    """Exchanges pairs of vertices while that lowers the cut; where blocks are full, single moves can't."""
    if csr.n > most:
        return block
    block = block.copy()
    near = np.zeros((csr.n, csr.n), np.int64)
    near[csr.rows(), csr.nbr] = csr.w
    at = np.arange(csr.n)
    load = np.bincount(block, csr.vw, k).astype(np.int64)
    for _ in range(4 * csr.n):
        ties = np.zeros((csr.n, k), np.int64)
        np.add.at(ties.T, block, near)
        d = ties[:, block] - ties[at, block][:, None]  # what u gains in v's block
        gain = d + d.T - 2 * near
        more = csr.vw[None, :] - csr.vw[:, None]
        fits = (load[block][:, None] + more <= bound) & (load[block][None, :] - more <= bound)
        gain[(block[:, None] == block[None, :]) | ~fits] = 0
        u, v = np.unravel_index(int(gain.argmax()), gain.shape)
        if gain[u, v] <= 0:
            break
        load[block[u]] += csr.vw[v] - csr.vw[u]
        load[block[v]] += csr.vw[u] - csr.vw[v]
        block[u], block[v] = block[v], block[u]
    return block


def rebalance(csr: Csr, block: np.ndarray, k: int, bound: int) -> np.ndarray:
    """Moves vertices out of blocks beyond the bound, least loss first; as a last resort all are packed anew by weight."""
    block = block.copy()
    load = np.bincount(block, csr.vw, k).astype(np.int64)
    stuck = False
    while (load > bound).any() and not stuck:
        stuck = True
        for b in np.flatnonzero(load > bound).tolist():
            inside = np.flatnonzero(block == b)
            moves = []
            for v in inside.tolist():
                s = np.bincount(block[csr.nbr[csr.indptr[v] : csr.indptr[v + 1]]], csr.w[csr.indptr[v] : csr.indptr[v + 1]], k)
                moves.append((s[b] - np.delete(s, b).max(initial=0), int(csr.vw[v]), v, s))
            for _, _, v, s in sorted(moves, key=lambda m: m[:3]):
                if load[b] <= bound:
                    break
                s = np.where(load + csr.vw[v] <= bound, s, -1.0)
                s[b] = -1
                if s.max() >= 0:
                    t = int(np.argmax(s - 1e-9 * load))
                    load[b] -= csr.vw[v]
                    load[t] += csr.vw[v]
                    block[v] = t
                    stuck = False
    if (load > bound).any():
        fresh, load = block.copy(), np.zeros(k, np.int64)
        for v in np.argsort(-csr.vw, kind="stable").tolist():
            t = block[v] if load[block[v]] + csr.vw[v] <= bound else int(np.argmin(load))
            fresh[v] = t
            load[t] += csr.vw[v]
        block = fresh
    return block


def _arcs_of(csr: Csr, who: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(position in ``who``, arc) of all arcs that leave these vertices, in their order."""
    d = csr.degrees()[who]
    at = np.repeat(np.arange(len(who)), d)
    return at, np.arange(len(at)) - np.repeat(np.cumsum(d) - d, d) + np.repeat(csr.indptr[who], d)


def _reached(ptr: np.ndarray, end: np.ndarray, cap: np.ndarray, start: np.ndarray, goal: np.ndarray) -> tuple[np.ndarray, int]:
    """Distance from ``start`` over arcs with room, -1 where none leads, and the distance at which a vertex of ``goal`` is met first, or -1."""
    level = np.full(len(goal), -1)
    rim, far = np.flatnonzero(start), 0
    level[rim] = 0
    while len(rim):
        if goal[rim].any():
            return level, far
        d = np.diff(ptr)[rim]
        arc = np.arange(int(d.sum())) - np.repeat(np.cumsum(d) - d, d) + np.repeat(ptr[rim], d)
        to = end[arc[cap[arc] > 0]]
        far += 1
        level[to[level[to] < 0]] = far
        rim = np.unique(to[level[to] == far])
    return level, -1


def _source_side(ptr: np.ndarray, end: np.ndarray, back: np.ndarray, cap: np.ndarray, out: np.ndarray, sink: np.ndarray) -> np.ndarray:
    """The smallest source side of a least cut, as flags: shortest augmenting paths by levels, until none is left.

    Arcs lie from ``ptr`` on, ``back`` is the arc against each; ``out`` and ``sink`` are what the source gives
    to a vertex and what it may give to the sink.
    """
    both = np.minimum(out, sink)
    out, sink = (out - both).tolist(), (sink - both).tolist()
    ends, backs, room, starts = end.tolist(), back.tolist(), cap.tolist(), ptr.tolist()
    while True:
        found, far = _reached(ptr, end, np.array(room, np.int64), np.array(out) > 0, np.array(sink) > 0)
        if far < 0:
            return found >= 0
        level, at = found.tolist(), starts[:-1].copy()
        for s in np.flatnonzero(np.array(out) > 0).tolist():
            path: list[int] = []
            v = s
            while out[s]:
                if level[v] == far and sink[v]:
                    flow = min(out[s], sink[v], *[room[x] for x in path]) if path else min(out[s], sink[v])
                    out[s] -= flow
                    sink[v] -= flow
                    for x in path:
                        room[x] -= flow
                        room[backs[x]] += flow
                    path, v = [], s
                    continue
                x, stop = at[v], starts[v + 1] if level[v] < far else 0
                while x < stop and not (room[x] and level[ends[x]] == level[v] + 1):
                    x += 1
                at[v] = x
                if x < stop:
                    path.append(x)
                    v = ends[x]
                elif path:
                    level[v] = -1
                    v = ends[backs[path.pop()]]
                else:
                    break


def flow_polish(csr: Csr, block: np.ndarray, a: int, b: int, bound: int, load: np.ndarray | None = None) -> np.ndarray:
    """Moves the border of two blocks to a least cut of a band around it that keeps both within the bound.

    The band is as wide as the room in the blocks lets it be.  ``load``: weights of blocks of which the graph is a part.
    """
    load = np.bincount(block, csr.vw, max(int(block.max()), a, b) + 1) if load is None else load
    mine = np.flatnonzero((block == a) | (block == b))
    at, arc = _arcs_of(csr, mine)
    other = block[csr.nbr[arc]]
    crosses = (other != block[mine][at]) & ((other == a) | (other == b))
    flag = np.zeros(len(mine), bool)
    flag[at[crosses]] = True
    rim = mine[flag]
    if not len(rim):
        return block
    band = np.zeros(csr.n, bool)
    for side, across in ((a, b), (b, a)):
        room, queue = bound - load[across], deque(rim[block[rim] == side].tolist())
        seen = np.zeros(csr.n, bool)
        seen[list(queue)] = True
        while queue:
            v = queue.popleft()
            if csr.vw[v] > room:
                break
            room -= csr.vw[v]
            band[v] = True
            near = csr.nbr[csr.indptr[v] : csr.indptr[v + 1]]
            near = near[(block[near] == side) & ~seen[near]]
            seen[near] = True
            queue.extend(near.tolist())
    inner = np.flatnonzero(band)
    if not len(inner):
        return block
    at, arc = _arcs_of(csr, inner)
    end, w = csr.nbr[arc], csr.w[arc]
    within = band[end]
    rest = [np.bincount(at[~within & (block[end] == x)], w[~within & (block[end] == x)], len(inner)).astype(np.int64) for x in (a, b)]
    place = np.zeros(csr.n, np.int64)
    place[inner] = np.arange(len(inner))
    src, dst = at[within], place[end[within]]
    # Arcs go by (src, dst), so the one against each is found by the order of (dst, src).
    back = np.empty(len(src), np.int64)
    back[np.lexsort((src, dst))] = np.arange(len(src))
    reach = _source_side(np.searchsorted(src, np.arange(len(inner) + 1)), dst, back, w[within], *rest)
    out = block.copy()
    out[inner] = np.where(reach, a, b)
    # Only arcs of the band change; those with both ends in it are met twice.
    times = np.where(within, 1, 2) * w
    lower = times[out[inner][at] != out[end]].sum() < times[block[inner][at] != block[end]].sum()
    moved = inner[out[inner] != block[inner]]
    gone = int(csr.vw[moved[block[moved] == a]].sum()) - int(csr.vw[moved[block[moved] == b]].sum())
    return out if lower and load[a] - gone <= bound and load[b] + gone <= bound else block


def flow_all_pairs(csr: Csr, block: np.ndarray, bound: int) -> np.ndarray:
    rows, k = csr.rows(), int(block.max(initial=0)) + 1
    low, high = np.minimum(block[rows], block[csr.nbr]), np.maximum(block[rows], block[csr.nbr])
    met = np.bincount(low * k + high, minlength=k * k).reshape(k, k)
    for a, b in zip(*[x.tolist() for x in np.nonzero(np.triu(met, 1))]):
        block = flow_polish(csr, block, a, b, bound)
    return block


# -- localized multi-try search ------------------------------------------------


class RandomWalkStop:
    """Stops when, with a mean gain below 0 since the last best state, a return to it is unlikely: s mu^2 > a sigma^2 + b."""

    def __init__(self, a: float, b: float):
        self.a, self.b = a, b
        self.reset()

    def reset(self) -> None:
        self.steps, self.mean, self.spread = 0, 0.0, 0.0

    def push(self, gain: float) -> bool:
        self.steps += 1
        d = gain - self.mean
        self.mean += d / self.steps
        self.spread += d * (gain - self.mean)
        variance = self.spread / (self.steps - 1) if self.steps > 1 else 0.0
        return self.mean < 0 and self.steps * self.mean**2 > self.a * variance + self.b


class ProbeTable:
    """Linear probing under a tabular hash that keeps neighbouring keys in one stretch of slots."""

    def __init__(self, capacity: int = 1024, low: int = 5, t: int = 10, bits: int = 30, seed: int = 1):
        self.low, self.t, self.bits, self.seed = low, t, bits, seed
        self.lookups = self.probes = 0
        self._reset(1 << max(6, (2 * capacity - 1).bit_length()))

    def _reset(self, size: int) -> None:
        self.key, self.value, self.used = np.full(size, -1, np.int64), np.zeros(size, np.int64), 0

    def _slot(self, key: int) -> int:
        mask = len(self.key) - 1
        at = int(tabular_hash_np(np.array([key]), self.t, self.bits, self.seed, self.low)[0]) & mask
        self.lookups += 1
        while self.key[at] not in (key, -1):
            self.probes += 1
            at = (at + 1) & mask
        return at

    def get(self, key: int, default: int) -> int:
        at = self._slot(key)
        return int(self.value[at]) if self.key[at] == key else default

    def __setitem__(self, key: int, value: int) -> None:
        at = self._slot(key)
        if self.key[at] == -1:
            self.used += 1
            if 2 * self.used > len(self.key):
                pairs = [(k, v) for k, v in zip(self.key.tolist(), self.value.tolist()) if k >= 0]
                self._reset(2 * len(self.key))
                for k, v in [*pairs, (key, value)]:
                    self[k] = v
                return
            self.key[at] = key
        self.value[at] = value

    def get_many(self, keys: np.ndarray, default: np.ndarray) -> np.ndarray:
        """As :meth:`get` of each key, with the same counts of lookups and probes."""
        mask = len(self.key) - 1
        at = tabular_hash_np(keys, self.t, self.bits, self.seed, self.low) & mask
        self.lookups += len(keys)
        away = np.arange(len(keys))
        while len(away):
            found = self.key[at[away]]
            away = away[(found != keys[away]) & (found != -1)]
            self.probes += len(away)
            at[away] = (at[away] + 1) & mask
        return np.where(self.key[at] == keys, self.value[at], default)

    def items(self):
        return [(k, v) for k, v in zip(self.key.tolist(), self.value.tolist()) if k >= 0]

    def nbytes(self) -> int:
        return self.key.nbytes + self.value.nbytes


class _ArrayStore:
    def __init__(self, n: int):
        self.value, self.lookups, self.probes = np.full(n, -1, np.int64), 0, 0

    def get(self, key: int, default: int) -> int:
        self.lookups += 1
        v = self.value[key]
        return default if v < 0 else int(v)

    def get_many(self, keys: np.ndarray, default: np.ndarray) -> np.ndarray:
        self.lookups += len(keys)
        v = self.value[keys]
        return np.where(v < 0, default, v)

    def __setitem__(self, key: int, value: int) -> None:
        self.value[key] = value

    def nbytes(self) -> int:
        return self.value.nbytes


class _DictStore(dict):
    """Beside it lies an array with the block of every vertex as the search sees it, for many keys at once."""

    lookups = probes = 0

    def __init__(self, block: np.ndarray):
        super().__init__()
        self.now = block.copy()

    def get_many(self, keys: np.ndarray, default: np.ndarray | None = None) -> np.ndarray:
        return self.now[keys]

    def __setitem__(self, key: int, value: int) -> None:
        super().__setitem__(key, value)
        self.now[key] = value

    def nbytes(self) -> int:
        return 100 * len(self) + self.now.nbytes


class _Kept:
    """Strengths to all blocks of the vertices of many arcs, a row for each that was counted, kept up to date by all moves."""

    def __init__(self, n: int, k: int):
        self.row, self.value, self.used = np.full(n, -1), np.zeros((64, k)), 0

    def add(self, who: np.ndarray, strength: np.ndarray) -> None:
        self.row[who] = np.arange(self.used, self.used + len(who))
        self.used += len(who)
        if self.used > len(self.value):
            self.value = np.concatenate([self.value, np.zeros((self.used, self.value.shape[1]))])
        self.value[self.row[who]] = strength

    def move(self, near: np.ndarray, weight: np.ndarray, own: int, to: int) -> None:
        if self.used:
            at = self.row[near]
            mine = at >= 0
            at, weight = at[mine], weight[mine]
            self.value[at, own] -= weight
            self.value[at, to] += weight


#: With more arcs than this a vertex's strengths are kept, not counted again, where the store counts no lookups.
KEPT_ARCS = 64


def block_store(kind: str, block: np.ndarray):
    """Where a search keeps the blocks that it changed: dict, array, probe (plain hash) or probe_local."""
    n = len(block)
    if kind == "dict":
        return _DictStore(block)
    if kind == "array":
        return _ArrayStore(n)
    return ProbeTable(256, low=5 if kind == "probe_local" else 0, bits=max(20, n.bit_length()))


def perform_moves(csr: Csr, block: np.ndarray, sizes: np.ndarray, bound: int, seeds: list[int], owned: np.ndarray | None, pe: int, stop_a: float = 1.0, stop_b: float | None = None, seed: int = 0, store: str = "dict", gain_mode: str = "recompute", max_steps: int = 0, mark: str = "on_move", stats: dict | None = None) -> list[tuple[int, int, int, int, int, int, int]]:
    """The local searches of one PE: rows (pe, call, step, vertex, from, to, local gain).

    Each seed starts a search of its own; only owned vertices move, each once;
    global blocks and sizes are read, never changed.  A search keeps its best
    prefix.  ``incremental`` mode keeps the strengths of queued vertices up to
    date instead of counting them again; the moves are the same.
    """
    rng = np.random.default_rng((seed, pe))
    k = len(sizes)
    moved = np.zeros(csr.n, bool)
    queued_once = np.zeros(csr.n, bool)
    changed = block_store(store, block)
    kept = _Kept(csr.n, k) if store == "dict" and gain_mode != "incremental" else None
    load = sizes.astype(np.int64).copy()
    ptr, nbr, w, vw = csr.indptr, csr.nbr, csr.w, csr.vw
    stop_b = math.log(max(csr.n, 2)) if stop_b is None else stop_b
    log: list[tuple] = []
    tried = 0

    def count(who: np.ndarray) -> np.ndarray:
        """The strength of each of ``who`` to each block, counted over all their arcs at once."""
        if len(who) == 1:
            a, b = ptr[who[0]], ptr[who[0] + 1]
            return np.bincount(changed.get_many(nbr[a:b], block[nbr[a:b]]), w[a:b], k)[None]
        d = ptr[who + 1] - ptr[who]
        end = d.cumsum()
        arc = (ptr[who] - end + d).repeat(d)
        arc += np.arange(len(arc))
        to = nbr[arc]
        at = changed.get_many(to, block[to])
        at = at + np.arange(0, len(who) * k, k).repeat(d)
        return np.bincount(at, w[arc], len(who) * k).reshape(-1, k)

    def strengths(who: np.ndarray) -> np.ndarray:
        if kept is None:
            return count(who)
        many = who[(ptr[who + 1] - ptr[who] > KEPT_ARCS) & (kept.row[who] < 0)]
        if len(many):
            kept.add(many, count(many))
        row = kept.row[who]
        if row.min() >= 0:
            return kept.value[row]
        out = np.empty((len(who), k))
        few = row < 0
        out[~few] = kept.value[row[~few]]
        out[few] = count(who[few])
        return out

    for call, root in enumerate(seeds):
        if moved[root] or (mark == "on_queue" and queued_once[root]):
            continue
        heap: list[tuple] = []
        stamp: dict[int, int] = {}
        ties: dict[int, float] = {}
        strength: dict[int, np.ndarray] = {}

        def push(who: np.ndarray) -> None:
            """Queues distinct vertices in their order."""
            if gain_mode == "incremental":
                new = [v for v in who.tolist() if v not in strength]
                if new:
                    strength.update(zip(new, count(np.array(new))))
                s = np.array([strength[v] for v in who.tolist()])
            else:
                s = strengths(who)
            at = np.arange(len(who))
            own = np.array([changed.get(v, b) for v, b in zip(who.tolist(), block[who].tolist())])
            stay = s[at, own]
            s[at, own] = -1
            s[load[None] + vw[who][:, None] > bound] = -1
            best_to = s.argmax(1)
            top = s[at, best_to]
            for v, loss, t, good in zip(who.tolist(), (stay - top).tolist(), best_to.tolist(), (top > 0).tolist()):
                stamp[v] = stamp.get(v, 0) + 1
                if good:
                    heapq.heappush(heap, (loss, ties.setdefault(v, rng.random()), v, t, stamp[v]))

        near = np.concatenate([[root], nbr[ptr[root] : ptr[root + 1]]])
        near = near[~moved[near]] if owned is None else near[~moved[near] & owned[near]]
        if len(near):
            queued_once[near] = True
            push(near)
        seq, total, best, best_at = [], 0, 0, 0
        rule = RandomWalkStop(stop_a, stop_b)
        while heap and not (max_steps and len(seq) >= max_steps):
            loss, _, v, t, st = heapq.heappop(heap)
            if moved[v] or st != stamp[v]:
                continue
            if load[t] + vw[v] > bound:
                push(np.array([v]))
                continue
            own = changed.get(v, int(block[v]))
            changed[v] = t
            near, weight = nbr[ptr[v] : ptr[v + 1]], w[ptr[v] : ptr[v + 1]]
            if kept is not None:
                kept.move(near, weight, own, t)
            moved[v] = True
            load[own] -= vw[v]
            load[t] += vw[v]
            gain = int(-loss)
            total += gain
            seq.append((v, own, t, gain))
            tried += 1
            if total > best:
                best, best_at = total, len(seq)
                rule.reset()
            elif rule.push(gain):
                break
            if gain_mode == "incremental":
                for u, x in zip(near.tolist(), weight.tolist()):
                    if u in strength:
                        strength[u][own] -= x
                        strength[u][t] += x
            near = near[~moved[near]] if owned is None else near[~moved[near] & owned[near]]
            if len(near):
                queued_once[near] = True
                push(near)
        for v, own, t, _ in reversed(seq[best_at:]):
            changed[v] = own
            if kept is not None:
                kept.move(nbr[ptr[v] : ptr[v + 1]], w[ptr[v] : ptr[v + 1]], t, own)
            load[t] -= vw[v]
            load[own] += vw[v]
        log += [(pe, call, step, v, own, t, gain) for step, (v, own, t, gain) in enumerate(seq[:best_at])]
    if stats is not None:
        stats["tried"] = stats.get("tried", 0) + tried
        stats["lookups"] = stats.get("lookups", 0) + changed.lookups
        stats["probes"] = stats.get("probes", 0) + changed.probes
        stats["bytes"] = max(stats.get("bytes", 0), changed.nbytes())
    return log


def replay(csr: Csr, block: np.ndarray, sizes: np.ndarray, bound: int, moves: list[tuple]) -> tuple[np.ndarray, int, list[int]]:
    """Applies sequences by (pe, call) with gains counted anew: each up to its best prefix that fits, so the cut never rises and no bound breaks."""
    block, load = block.copy(), sizes.astype(np.int64).copy()
    gained, touched = 0, []
    k = len(load)
    i = 0
    moves = sorted(moves)
    while i < len(moves):
        j = i
        while j < len(moves) and moves[j][:2] == moves[i][:2]:
            j += 1
        total = best = best_at = 0
        done = []
        for _, _, _, v, own, t, _ in moves[i:j]:
            if block[v] != own or load[t] + csr.vw[v] > bound:
                break
            a, b = csr.indptr[v], csr.indptr[v + 1]
            s = np.bincount(block[csr.nbr[a:b]], csr.w[a:b], k)
            total += int(s[t] - s[own])
            block[v] = t
            load[own] -= csr.vw[v]
            load[t] += csr.vw[v]
            done.append((v, own, t))
            if total > best:
                best, best_at = total, len(done)
        for v, own, t in reversed(done[best_at:]):
            block[v] = own
            load[t] -= csr.vw[v]
            load[own] += csr.vw[v]
        gained += best
        touched += [v for v, _, _ in done[:best_at]]
        i = j
    return block, gained, touched


def boundary(csr: Csr, block: np.ndarray) -> np.ndarray:
    return border(csr, block)


def todo_order(csr: Csr, todo: np.ndarray, p: int, seed: int) -> list[list[int]]:
    """A shuffled bucket of the todo list for each PE."""
    ids = csr.ids[todo]
    pe = mix_np(ids, seed + 1) % p
    order = np.lexsort((ids, mix_np(ids, seed)))
    out: list[list[int]] = [[] for _ in range(p)]
    for v, q in zip(todo[order].tolist(), pe[order].tolist()):
        out[q].append(v)
    return out


def own_balls(csr: Csr, buckets: list[list[int]], seed: int, radius: int = 1 << 30) -> np.ndarray:
    """The PE that may move each vertex: that of the nearest seed; -1 beyond the radius."""
    owner = np.full(csr.n, -1)
    for pe, seeds in enumerate(buckets):
        owner[seeds] = pe
    rim = np.flatnonzero(owner >= 0)
    src = csr.rows()
    for _ in range(radius):
        flag = np.zeros(csr.n, bool)
        flag[rim] = True
        arc = np.flatnonzero(flag[src] & (owner[csr.nbr] < 0))
        if not len(arc):
            break
        v, pe = csr.nbr[arc], owner[src[arc]]
        order = np.lexsort((mix_np(pe * 1_000_003 + csr.ids[v], seed), v))
        first = np.ones(len(order), bool)
        first[1:] = v[order][1:] != v[order][:-1]
        rim = v[order[first]]
        owner[rim] = pe[order[first]]
    return owner


def _alone(csr: Csr, block: np.ndarray, u: int, target: int, own: int, few: int = 64) -> tuple:
    """What u gains by a move of its own; its neighbours in block ``own`` and the weights of their edges, as lists up to ``few`` arcs."""
    arcs = slice(csr.indptr[u], csr.indptr[u + 1])
    near, w = csr.nbr[arcs], csr.w[arcs]
    at = block[near]
    if len(near) > few:
        stay = at == own
        return int(w[at == target].sum()) - int(w[stay].sum()), near[stay], w[stay]
    gain, inner, ties = 0, [], []
    for x, b, s in zip(near.tolist(), at.tolist(), w.tolist()):
        if b == own:
            gain -= s
            inner.append(x)
            ties.append(s)
        elif b == target:
            gain += s
    return gain, inner, ties


def _hill(csr: Csr, block: np.ndarray, load: np.ndarray, bound: int, v: int, most: int) -> tuple[list[int], int, int]:
    """(vertices, target, gain): a connected set around v in its block whose joint move to v's best other block pays, or no vertices.

    The set grows by the vertex that adds most to the gain of the joint move, as far as ``most`` vertices.
    """
    own = int(block[v])
    a, b = csr.indptr[v], csr.indptr[v + 1]
    ties = np.bincount(block[csr.nbr[a:b]], csr.w[a:b], len(load))
    ties[own] = -1
    target = int(ties.argmax())
    if ties[target] <= 0:
        return [], own, 0
    hill, inside, total, weight = [], set(), 0, 0
    # The blocks stay as they are while a hill grows, so what a vertex gains by itself is told once.
    alone: dict[int, tuple] = {}
    # What the joint move would gain if the vertex joined: its ties to the target and the hill less those to the rest of its block.
    reach: dict[int, int] = {v: 0}
    while reach and len(hill) < most:
        best, best_gain = -1, None
        for u, shared in reach.items():
            if u not in alone:
                alone[u] = _alone(csr, block, u, target, own)
            gain = alone[u][0] + 2 * shared
            if best_gain is None or gain > best_gain:
                best, best_gain = u, gain
        if load[target] + weight + csr.vw[best] > bound:
            break
        hill.append(best)
        inside.add(best)
        del reach[best]
        total += best_gain
        weight += int(csr.vw[best])
        if total > 0:
            return hill, target, total
        for u, w in zip(*(x if isinstance(x, list) else x.tolist() for x in alone[best][1:])):
            if u not in inside and (u in reach or len(reach) < 4 * most):
                reach[u] = reach.get(u, 0) + w
    return [], own, 0


def hill_climb(csr: Csr, block: np.ndarray, k: int, bound: int, p: int, seed: int, rounds: int = 8, most: int = 16) -> np.ndarray:
    """The rival's refinement: PEs move vertices, or hills of up to ``most`` that pay together, each on its own copy of the blocks and weights.

    PEs don't see each other's moves of a round, so the balance may break and the cut may rise.
    """
    block = block.copy()
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        rim = boundary(csr, block)
        if not len(rim):
            break
        gained, merged = 0, block.copy()
        for part in np.array_split(rng.permutation(rim), p):
            mine, load = block.copy(), np.bincount(block, csr.vw, k).astype(np.int64)
            for v in part.tolist():
                hill, target, gain = _hill(csr, mine, load, bound, v, most)
                if hill:
                    own, weight = int(mine[v]), int(csr.vw[hill].sum())
                    mine[hill] = target
                    load[own] -= weight
                    load[target] += weight
                    gained += gain
            changed = mine != block
            merged[changed] = mine[changed]
        block = merged
        if gained <= 0:
            break
    return block
