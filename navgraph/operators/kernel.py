"""The layered navigable graph of one shard: search, insertion, deletion by marking, slot reuse, repair. numpy, no Spark.

A slot keeps its number, level and (until it is reused) its lists when its point is marked deleted; marked slots are walked
through but never returned. All ties go to the smaller slot. Distances are squared internally; alpha multiplies the distance.
"""

from __future__ import annotations

import hashlib
import heapq
import math
from collections import Counter, deque

import numpy as np
import pyarrow as pa

from navgraph.operators.repair import STRATEGIES, Strategy
from navgraph.schema import INDEX, arrow_schema

try:  # einsum without its dispatch, which costs as much as a short product
    from numpy._core.multiarray import c_einsum as einsum
except ImportError:
    from numpy import einsum


def level_of(label: int, m: int) -> int:
    u = (int(hashlib.md5(f"lvl:{label}".encode()).hexdigest()[:8], 16) + 1) / 4294967297
    return int(math.floor(-math.log(u) / math.log(m)))


class GraphKernel:
    def __init__(self, dim: int, m: int = 16, m0: int | None = None, ef_construction: int = 200, metric: str = "l2", order: str = "fifo", extend: bool = False, fill: bool = False, drop_marked: bool = False):
        """order: which marked slot is reused first. extend: an insertion's candidates include their neighbours. fill: places left by
        the pruning go to the nearest of those it dropped. drop_marked: marked slots are no candidates of a repair."""
        self.dim, self.m, self.m0, self.ef, self.metric, self.order = dim, m, m0 or 2 * m, ef_construction, metric, order
        self.extend, self.fill, self.drop_marked = extend, fill, drop_marked
        self.vec = np.zeros((0, dim))
        self.label: list[int] = []
        self.version: list[int] = []
        self.level: list[int] = []
        self.nbrs: list[list[list[int]]] = []  # slot, layer
        self.marked: dict[int, int] = {}  # slot and the number of its deletion, in that order
        self.marked_slot: dict[int, int] = {}  # label and its slot that was marked last
        self.slot_of: dict[int, int] = {}
        self.entry, self.reuses, self.sequence = -1, 0, 0
        self.count: Counter = Counter()
        self.walks: list[tuple[int, set[int], np.ndarray]] | None = None  # kept walks, of a graph that doesn't change any more

    # ---- distances and selection
    def cap(self, layer: int) -> int:
        return self.m0 if layer == 0 else self.m

    def prepared(self, v) -> np.ndarray:
        v = np.asarray(v, float)
        if self.metric == "cosine":
            n = math.sqrt(float(v @ v))
            return v / n if n else v
        return v

    def distances(self, q: np.ndarray, slots, kind: str = "search") -> np.ndarray:
        self.count[kind] += len(slots)
        x = self.vec.take(slots, 0)
        if self.metric == "ip":
            return -(x @ q)
        x -= q
        return einsum("ij,ij->i", x, x)

    def prune(self, centre: np.ndarray, candidates: list[int], cap: int, alpha: float = 1.0, kind: str = "prune") -> list[int]:
        """From the nearest candidate on, those to which no kept one is, alpha times, nearer than the centre.

        Every kept candidate rules out others in one step; counted are the distances that a reading one by one evaluates.
        """
        if not len(candidates):
            return []
        own = np.asarray(candidates)
        d = self.distances(centre, own, kind)
        order = np.lexsort((own, d))
        own, d = own.take(order), d.take(order)
        x, factor, ip, n = self.vec.take(own, 0), alpha * alpha if self.metric != "ip" else 1.0, self.metric == "ip", len(own)
        # Only those still open stay in x and d; `at` has their places.
        at, last, kept = np.arange(n), 0, []
        while True:
            last = int(at[0])
            kept.append(last)
            if len(kept) == cap or len(at) == 1:
                break
            rest = x[1:]
            if ip:
                apart = -(rest @ x[0])
            else:
                diff = rest - x[0]
                apart = einsum("ij,ij->i", diff, diff)
            if factor != 1.0:
                apart *= factor
            left = (apart >= d[1:]).nonzero()[0]
            if not len(left):
                break
            left += 1
            x, d, at = x.take(left, 0), d.take(left), at.take(left)
        end = last if len(kept) == cap else n - 1
        self.count[kind] += end * len(kept) - sum(kept)
        chosen = own.take(kept).tolist()
        if self.fill and len(chosen) < cap:
            chosen += [c for c in own.tolist() if c not in set(chosen)][: cap - len(chosen)]
        return chosen

    # ---- search
    def reached(self, start: int, layer: int = 0) -> set[int]:
        """Slots that a walk over a layer's lists from `start` comes to."""
        nbrs, seen, todo = self.nbrs, {start}, [start]
        while todo:
            layers = nbrs[todo.pop()]
            if layer < len(layers):
                for n in layers[layer]:
                    if n not in seen:
                        seen.add(n)
                        todo.append(n)
        return seen

    def walked(self, start: int) -> np.ndarray:
        """reached() in layer 0, ascending. Of kept walks those serve that lead to `start` and that it leads back to."""
        if self.walks is None:
            return np.sort(np.fromiter(self.reached(start), np.int64))
        goals = {s: slots for s, seen, slots in self.walks if start in seen}
        seen, todo = {start}, [start]
        while todo:
            s = todo.pop()
            if s in goals:
                return goals[s]
            for n in self.nbrs[s][0]:
                if n not in seen:
                    seen.add(n)
                    todo.append(n)
        self.walks.append((start, seen, np.sort(np.fromiter(seen, np.int64))))
        return self.walks[-1][2]

    def search_layer(self, q: np.ndarray, entries: list[int], ef: int, layer: int) -> list[tuple[float, int]]:
        """At most ef nearest visited slots, ascending."""
        if ef >= len(self.label):  # such a beam drops nothing: all that can be walked to is visited, whatever the order
            slots = np.sort(np.fromiter(set().union(*(self.reached(s, layer) for s in entries)), np.int64))
            d = self.distances(q, slots)
            order = np.lexsort((slots, d))
            return list(zip(d[order].tolist(), slots[order].tolist(), strict=True))
        push, pop, replace, nbrs, ip = heapq.heappush, heapq.heappop, heapq.heapreplace, self.nbrs, self.metric == "ip"
        take, asked = self.vec.take, len(entries)
        seen = set(entries)
        d = self.distances(q, entries)
        frontier = list(zip(d.tolist(), entries, strict=True))
        heapq.heapify(frontier)
        best = [(-x, -s) for x, s in frontier]
        heapq.heapify(best)
        while len(best) > ef:
            pop(best)
        full = len(best) >= ef
        while frontier:
            x, s = pop(frontier)
            if full and x > -best[0][0]:
                break
            layers = nbrs[s]
            new = [n for n in layers[layer] if n not in seen] if layer < len(layers) else None
            if not new:
                continue
            seen.update(new)
            asked += len(new)
            v = take(new, 0)
            if ip:
                d = -(v @ q)
            else:
                v -= q
                d = einsum("ij,ij->i", v, v)
            for y, n in zip(d.tolist(), new):  # noqa: B905
                if not full:
                    push(best, (-y, -n))
                    push(frontier, (y, n))
                    full = len(best) >= ef
                elif (-y, -n) > best[0]:
                    replace(best, (-y, -n))
                    push(frontier, (y, n))
        self.count["search"] += asked - len(entries)
        return sorted([(-x, -s) for x, s in best])

    def descend(self, q: np.ndarray, layer: int) -> list[int]:
        """From the entry point down to just above `layer`, keeping the nearest."""
        at = [self.entry]
        for up in range(self.level[self.entry], layer, -1):
            at = [self.search_layer(q, at, 1, up)[0][1]]
        return at

    def knn(self, q, k: int, ef: int) -> list[tuple[float, int]]:
        """(distance, slot) of the k nearest live points that are found."""
        if self.entry < 0:
            return []
        q = self.prepared(q)
        if max(ef, k) >= len(self.label):
            slots = self.walked(self.descend(q, 0)[0])
            d = self.distances(q, slots)
            if self.marked:
                good = ~np.isin(slots, np.fromiter(self.marked, np.int64))
                slots, d = slots[good], d[good]
            if len(d) > k:
                near = d <= np.partition(d, k - 1)[k - 1]
                slots, d = slots[near], d[near]
            order = np.lexsort((slots, d))[:k]
            live = list(zip(d[order].tolist(), slots[order].tolist(), strict=True))
        else:
            found = self.search_layer(q, self.descend(q, 0), max(ef, k), 0)
            live = [(x, s) for x, s in found if s not in self.marked][:k]
        return [(x if self.metric == "ip" else math.sqrt(max(x, 0.0)), s) for x, s in live] if self.metric != "cosine" else [(x / 2, s) for x, s in live]

    def enumerate_found(self) -> set[int]:
        """Live slots that a search for everything returns; the beam holds as many as there are slots, marked ones too."""
        if self.entry < 0:
            return set()
        found = self.reached(self.descend(self.vec[self.entry], 0)[0])
        self.count["search"] += len(found)
        return found - self.marked.keys()

    # ---- growth
    def link(self, slot: int, chosen: list[int], layer: int) -> None:
        """slot's list, and slot in the lists of those chosen; a full list is pruned with alpha 1."""
        self.nbrs[slot][layer] = list(chosen)
        for c in chosen:
            own = self.nbrs[c][layer]
            if slot in own:
                continue
            own.append(slot)
            if len(own) > self.cap(layer):
                self.nbrs[c][layer] = self.prune(self.vec[c], own, self.cap(layer), 1.0, "connect")

    def _place(self, slot: int, top: int) -> None:
        """Layered insertion of a slot whose vector is set; never returns the slot itself."""
        q = self.vec[slot]
        at = self.descend(q, top)
        for layer in range(min(top, self.level[self.entry]), -1, -1):
            found = [s for _, s in self.search_layer(q, at, self.ef, layer)]
            others = [s for s in found if s != slot]
            if self.extend:
                others = sorted({*others, *(n for s in others for n in self.nbrs[s][layer] if n != slot)})
            self.link(slot, self.prune(q, others, self.m), layer)
            at = found or at

    def insert(self, label: int, v, version: int = 0) -> int:
        slot, level = len(self.label), level_of(label, self.m)
        if slot >= len(self.vec):
            self.vec = np.concatenate((self.vec, np.zeros((max(64, slot), self.dim))))
        self.vec[slot] = self.prepared(v)
        self.label.append(label)
        self.version.append(version)
        self.level.append(level)
        self.nbrs.append([[] for _ in range(level + 1)])
        self.slot_of[label] = slot
        if self.entry < 0:
            self.entry = slot
            return slot
        self._place(slot, level)
        if level > self.level[self.entry]:
            self.entry = slot
        return slot

    # ---- deletion and reuse
    def mark_deleted(self, label: int) -> bool:
        slot = self.slot_of.pop(label, None)
        if slot is None:
            return False
        self.marked[slot] = self.sequence
        self.marked_slot[label] = slot
        self.sequence += 1
        return True

    def unmark(self, label: int) -> bool:
        """Brings back a marked point, unless its slot was reused or its label is live again."""
        slot = self.marked_slot.get(label)
        if slot is None or slot not in self.marked or self.label[slot] != label or label in self.slot_of:
            return False
        del self.marked[slot], self.marked_slot[label]
        self.slot_of[label] = slot
        return True

    def next_free(self) -> int | None:
        """The slot that was marked first (fifo) or last (lifo)."""
        return next(iter(self.marked) if self.order == "fifo" else reversed(self.marked), None)

    def repair_slot(self, d: int, v, strategy: Strategy, place: bool = True) -> dict[int, dict[int, list[int]]]:
        """New lists by layer and target. The slot's vector becomes `v` first: in candidate sets it is the new point. All
        lists of a layer are computed from those before the repair, then written."""
        self.vec[d] = self.prepared(v)
        out: dict[int, dict[int, list[int]]] = {}
        for layer in range(self.level[d] + 1):
            lists = lambda s: self.nbrs[s][layer] if layer < len(self.nbrs[s]) else []  # noqa: B023, E731
            one = lists(d)
            mutual = [v for v in one if d in lists(v)]
            chosen = list(one) if strategy.targets == "out" else mutual
            two = {n for v in one for n in lists(v)} | set(one) if strategy.pool == "twohop" or strategy.targets == "mutual+twohop" else set()
            if strategy.targets == "mutual+twohop":
                chosen = sorted(set(mutual) | {w for w in two if w != d and d in lists(w)})
            new = {}
            for u in chosen:
                pool = (two if strategy.pool == "twohop" else set(lists(u)) | set(one)) | {d}
                pool = sorted(s for s in pool if s != u and (s == d or not self.drop_marked or s not in self.marked))
                self.count["candidates"] += len(pool)
                new[u] = self.prune(self.vec[u], pool, self.cap(layer), strategy.alpha)
            out[layer] = new
            if place:
                for u, own in new.items():
                    self.nbrs[u][layer] = own
        return out

    def update_slot(self, d: int, v, label: int, version: int = 0) -> None:
        """The new point takes the slot, its level and its place in the layers; the entry point stays who it is."""
        self.marked.pop(d, None)
        if self.marked_slot.get(self.label[d]) == d:
            del self.marked_slot[self.label[d]]
        self.vec[d] = self.prepared(v)
        self.label[d], self.version[d] = label, version
        self.slot_of[label] = d
        self._place(d, self.level[d])

    def replace_update(self, label: int, v, strategy: Strategy | str, version: int = 0, slot: int | None = None) -> int:
        strategy = STRATEGIES[strategy] if isinstance(strategy, str) else strategy
        d = self.next_free() if slot is None else slot
        if d is None:
            return self.insert(label, v, version)
        self.repair_slot(d, v, strategy)
        self.update_slot(d, v, label, version)
        self.reuses += 1
        return d

    def upsert(self, label: int, v, strategy: Strategy | str) -> int:
        version = self.version[self.slot_of[label]] + 1 if label in self.slot_of else 0
        self.mark_deleted(label)
        return self.replace_update(label, v, strategy, version)

    def compact(self, strategy: Strategy | str = "mutual_gamma") -> int:
        """Drops marked slots and numbers the others anew, after repairing their mutual neighbours without a newcomer; returns
        how many. The entry point's slot stays while it is marked."""
        strategy = STRATEGIES[strategy] if isinstance(strategy, str) else strategy
        gone = [s for s in self.marked if s != self.entry]
        for d in gone:
            for layer in range(self.level[d] + 1):
                one = self.nbrs[d][layer]
                for u in [u for u in one if d in self.nbrs[u][layer]]:
                    pool = sorted((set(self.nbrs[u][layer]) | set(one)) - {u, d})
                    self.nbrs[u][layer] = self.prune(self.vec[u], pool, self.cap(layer), strategy.alpha)
        dead = set(gone)
        keep = [s for s in range(len(self.label)) if s not in dead]
        new = {s: i for i, s in enumerate(keep)}
        self.nbrs = [[[new[n] for n in own if n in new] for own in self.nbrs[s]] for s in keep]
        self.vec = self.vec[keep]
        self.label, self.version, self.level = ([x[s] for s in keep] for x in (self.label, self.version, self.level))
        self.marked = {new[s]: q for s, q in self.marked.items() if s in new}
        self.marked_slot = {self.label[s]: s for s in self.marked}
        self.slot_of = {x: new[s] for x, s in self.slot_of.items()}
        self.entry = new.get(self.entry, -1)
        return len(gone)

    # ---- measures
    def live(self) -> list[int]:
        return [s for s in range(len(self.label)) if s not in self.marked]

    def unreachable_degree(self) -> set[int]:
        """Live slots without an in-edge in any layer, but for the entry point."""
        into = {n for layers in self.nbrs for own in layers for n in own}
        return {s for s in self.live() if s not in into and s != self.entry}

    def unreachable_bfs(self) -> set[int]:
        """Live slots that no walk over edges of all layers reaches from the entry point."""
        seen, todo = {self.entry}, deque([self.entry])
        while todo:
            for own in self.nbrs[todo.popleft()]:
                for n in own:
                    if n not in seen:
                        seen.add(n)
                        todo.append(n)
        return set(self.live()) - seen

    def unreachable_search(self) -> set[int]:
        return set(self.live()) - self.enumerate_found() - {self.entry}

    def health(self) -> dict[str, int]:
        """Violations: lists over their cap, loops, repeated or dangling ids."""
        bad: Counter = Counter()
        n = len(self.label)
        for s, layers in enumerate(self.nbrs):
            for layer, own in enumerate(layers):
                bad["over_cap"] += len(own) > self.cap(layer)
                bad["loop"] += s in own
                bad["repeated"] += len(set(own)) < len(own)
                bad["dangling"] += sum(not 0 <= x < n or layer > self.level[x] for x in own)
            bad["level"] += len(layers) != self.level[s] + 1
        return dict(bad)

    # ---- the index table
    def table(self, role: str, shard: int, shards: int = 1) -> pa.Table:
        """One row per slot, from flat arrays."""
        n = len(self.label)
        stats = {"entry": 1.0, "reuses": float(self.reuses), "m": float(self.m), "m0": float(self.m0), "ef": float(self.ef), "sequence": float(self.sequence), "metric": float(("l2", "ip", "cosine").index(self.metric)), "lifo": float(self.order == "lifo"), "shards": float(shards), **{f"work_{k}": float(v) for k, v in self.count.items()}}
        inner = np.fromiter((len(own) for layers in self.nbrs for own in layers), np.int64)
        outer = np.fromiter((len(layers) for layers in self.nbrs), np.int64, n)
        offsets = lambda sizes: pa.array(np.concatenate(([0], np.cumsum(sizes))).astype(np.int32))
        flat = np.fromiter((x for layers in self.nbrs for own in layers for x in own), np.int64, int(inner.sum()))
        schema = arrow_schema(INDEX)
        columns = {
            "role": pa.array([role] * n, pa.string()), "shard": pa.array(np.full(n, shard, np.int32)), "slot": pa.array(np.arange(n)), "label": pa.array(self.label, pa.int64()), "vec": pa.ListArray.from_arrays(offsets(np.full(n, self.dim)), pa.array(self.vec[:n].astype(np.float32).ravel())),
            "version": pa.array(self.version, pa.int64()), "level": pa.array(self.level, pa.int32()), "deleted_seq": pa.array([self.marked.get(s) for s in range(n)], pa.int64()), "entry": pa.array([s == self.entry for s in range(n)], pa.bool_()),
            "nbrs": pa.ListArray.from_arrays(offsets(outer), pa.ListArray.from_arrays(offsets(inner), pa.array(flat))), "stats": pa.array([list(stats.items()) if s == self.entry else None for s in range(n)], schema.field("stats").type),
        }
        return pa.table([columns[f.name].cast(f.type) for f in schema], schema=schema)

    @classmethod
    def from_table(cls, table: pa.Table) -> GraphKernel:
        table = table.sort_by("slot").combine_chunks()
        column = lambda c: table.column(c).combine_chunks() if isinstance(table.column(c), pa.ChunkedArray) else table.column(c)
        entry = int(np.flatnonzero(column("entry").to_numpy(zero_copy_only=False))[0])
        stats = dict(column("stats")[entry].as_py())
        vec = column("vec")
        x = vec.flatten().to_numpy().astype(np.float64).reshape(len(vec), -1)
        g = cls(x.shape[1], int(stats["m"]), int(stats["m0"]), int(stats["ef"]), ("l2", "ip", "cosine")[int(stats["metric"])], "lifo" if stats.get("lifo") else "fifo")
        g.vec = x
        g.label, g.version, g.level = (column(c).to_pylist() for c in ("label", "version", "level"))
        outer = column("nbrs")
        inner = outer.flatten()
        flat, cut, at = inner.flatten().to_numpy().tolist(), np.concatenate(([0], np.cumsum(inner.value_lengths().to_numpy()))).tolist(), np.concatenate(([0], np.cumsum(outer.value_lengths().to_numpy()))).tolist()
        g.nbrs = [[flat[cut[k] : cut[k + 1]] for k in range(a, b)] for a, b in zip(at[:-1], at[1:], strict=True)]
        seq = column("deleted_seq").to_pylist()
        g.marked = dict(sorted(((s, q) for s, q in enumerate(seq) if q is not None), key=lambda x: x[1]))
        g.marked_slot = {g.label[s]: s for s in g.marked}
        g.slot_of = {label: s for s, (label, q) in enumerate(zip(g.label, seq, strict=True)) if q is None}
        g.entry, g.reuses, g.sequence = entry, int(stats["reuses"]), int(stats["sequence"])
        g.count = Counter({k[5:]: int(v) for k, v in stats.items() if k.startswith("work_")})
        return g
