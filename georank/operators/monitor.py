"""The approximate monitor, one count-based window at a time, as pure functions over numpy arrays.

Work is in whole numerators (doubled where slack is odd), so no division happens before output. Queries come as lists
of what they reach: object ids and contributions in rank-list order, cut into blocks. The set-oriented part (matching, rank lists)
is prepared by Spark; what is inherently sequential runs in one stateful operator per monitor.

State: the m (+ buffer) held objects with exact values, `ub_next` (a bound on everyone else's value), the live window's queries,
and the ledger of touched objects with their last evaluation.
"""

from __future__ import annotations

import heapq
from collections import deque
from dataclasses import dataclass, field
from time import perf_counter


@dataclass
class Reached:
    """One query's reach: contributions by object, and blocks (best contribution, members) in rank-list order."""

    value: dict[int, int]
    blocks: list[tuple[int, list[int]]] = field(default_factory=list)


def reached(oids: list[int], values: list[int], block: int) -> Reached:
    return Reached(dict(zip(oids, values)), [(values[i], oids[i : i + block]) for i in range(0, len(oids), block)])


def safe_rank2(n: int, ub_next: int, gain: int, floor: int) -> int:
    """The largest doubled rank estimate at which a held object, at the floor before the new query, is not overtaken."""
    return 2 * (n + 1) - (ub_next + gain - floor)


class Monitor:
    """modes: block_level, object_level, aging, reuse, naive gain; all give the same answers at different cost."""

    def __init__(self, n: int, w: int, m: int, cmax: int, block: int = 128, buffer: int = 0, block_level: bool = True, object_level: bool = True, aging: bool = False, reuse: bool = True, naive: bool = False, retain: int | None = None, by_value: bool = True):
        self.n, self.w, self.m, self.cmax, self.block, self.buffer = n, w, m, cmax, block, buffer
        self.block_level, self.object_level, self.aging, self.reuse, self.naive = block_level, object_level, aging, reuse, naive
        self.retain, self.by_value = w // 3 if retain is None else min(retain, w), by_value  # older windows share no query
        self.live: deque[Reached] = deque()
        self.touch: dict[int, int] = {}
        self.held: dict[int, int] = {}
        self.ub_next = 0
        self.seen: dict[int, tuple[int, int]] = {}
        self.shift = 0

    def _exact(self, oid: int) -> tuple[int, bool]:
        """The value over the live window; from the last evaluation if few enough shifts ago, else from all its queries."""
        old = self.seen.get(oid)
        if self.reuse and old is not None and self.shift - old[1] <= self.retain and self.shift - old[1] <= len(self.gone):
            back = self.shift - old[1]
            v = old[0]
            for i in range(back):
                v += self.live[len(self.live) - 1 - i].value.get(oid, 0) - self.gone[len(self.gone) - 1 - i].value.get(oid, 0)
            return v, True
        return sum(q.value.get(oid, 0) for q in self.live), False

    def _settled(self, new: Reached, gain: int, floor: int) -> bool:
        """Whether no outsider can overtake a result object. By value: the m-th value exceeds the best outsider's and its gain. By rank: every
        result object is reached by the new query at a rank estimate below the safe rank, so it is at least as much above the floor."""
        best = self._order(self.held)[: self.m]
        if self.by_value:
            return min((self.held[o] for o in best), default=0) > self.ub_next + gain
        safe = safe_rank2(self.n, self.ub_next, gain, floor)
        return all(o in new.value and 2 * (self.n + 1) - new.value[o] < safe for o in best)

    def _order(self, values: dict[int, int]) -> list[int]:
        return sorted(values, key=lambda o: (-values[o], o))

    def start(self, first: list[Reached]) -> list[tuple[int, int]]:
        """The first full window, exactly."""
        self.live.extend(first)
        self.gone: deque[Reached] = deque(maxlen=max(1, self.retain))
        total: dict[int, int] = {}
        for q in first:
            for o, c in q.value.items():
                total[o] = total.get(o, 0) + c
                self.touch[o] = self.touch.get(o, 0) + 1
        best = self._order(total)
        self.held = {o: total[o] for o in best[: self.m + self.buffer]}
        self.ub_next = max((total[o] for o in best[self.m + self.buffer :]), default=0)
        if self.aging:
            self.seen = {o: (v, 0) for o, v in total.items()}
        return self._result()

    def _result(self) -> list[tuple[int, int]]:
        return [(o, self.held[o]) for o in self._order(self.held)[: self.m]]

    def step(self, new: Reached) -> tuple[list[tuple[int, int]], dict]:
        """Shift the window by one query: the result, and what it cost, in objects and in seconds by phase."""
        begun = perf_counter()
        self.shift += 1
        old = self.live.popleft()
        self.gone.append(old)
        for o in old.value:  # deduct the expired query
            self.touch[o] -= 1
            if not self.touch[o]:
                del self.touch[o]
                self.seen.pop(o, None)
        for o in self.held:
            self.held[o] -= old.value.get(o, 0)
        self.live.append(new)
        for o in new.value:
            self.touch[o] = self.touch.get(o, 0) + 1
        size = self.m + self.buffer
        order = self._order(self.held)
        floor = self.held[order[self.m - 1]] if len(order) >= self.m else None
        for o in self.held:
            self.held[o] += new.value.get(o, 0)

        # Gains of blocks: the best new contribution, less nothing unless all of a block surely loses; walked in order.
        heap: list[tuple[int, int]] = []
        g_block, cursor = 0, 0
        while cursor < len(new.blocks):
            best, members = new.blocks[cursor]
            if best <= g_block:
                break
            loss = min((old.value.get(o, 0) for o in members), default=0)
            gain = self.cmax if self.naive else best - loss
            heapq.heappush(heap, (-gain, cursor))
            g_block = max(g_block, gain)
            cursor += 1

        outcome = None
        if floor is not None and len(self.held) >= size:
            if self.block_level and not self.naive and self._settled(new, g_block, floor):
                outcome, up = "block", g_block
            blocks_done = perf_counter()
            if outcome is None and self.object_level:
                g_obj, opened = 0, 0
                work, at = list(heap), cursor
                heapq.heapify(work)
                while True:
                    while at < len(new.blocks) and new.blocks[at][0] > g_obj:  # blocks not walked may still matter
                        heapq.heappush(work, (-new.blocks[at][0], at))
                        at += 1
                    if not work or -work[0][0] <= g_obj:
                        break
                    _, b = heapq.heappop(work)
                    opened += 1
                    for o in new.blocks[b][1]:
                        if o not in self.held:
                            g_obj = max(g_obj, new.value[o] - old.value.get(o, 0))
                if self._settled(new, g_obj, floor):
                    outcome, up = "object", g_obj
        else:
            blocks_done = perf_counter()
        objects_done = perf_counter()
        spent = {"t_block": blocks_done - begun, "t_object": objects_done - blocks_done, "t_valid": 0.0}
        if outcome:
            self.ub_next += up
            return self._result(), {"outcome": outcome, "opq_validation": 0, "opq_total": len(self.held), "reused": 0} | spent

        # Validation: outsiders that may now reach the m-th value, each by its own bound, best bound first.
        ranked = self._order(self.held)
        bar = (self.held[ranked[self.m - 1]], ranked[self.m - 1]) if len(ranked) >= size and len(ranked) >= self.m else None
        bounds = []
        for o in self.touch:
            if o in self.held:
                continue
            gain = new.value.get(o, 0) - old.value.get(o, 0)
            ub = self.ub_next + gain
            if self.aging and o in self.seen:
                v, at = self.seen[o]
                ub = min(ub, v + (self.shift - at) * self.cmax)
            bounds.append((-ub, o))
        bounds.sort()
        evaluated, reused, rest = 0, 0, 0
        for neg, o in bounds:
            if bar is not None and (-neg, -o) < (bar[0], -bar[1]):
                rest = max(rest, -neg)
                continue
            v, again = self._exact(o)
            evaluated += 1
            reused += again
            self.seen[o] = (v, self.shift)
            self.held[o] = v
            order = self._order(self.held)
            if len(order) > size:
                rest = max(rest, self.held.pop(order[-1]))
                order.pop()
            if len(order) >= size:
                bar = (self.held[order[self.m - 1]], order[self.m - 1])
        for o in [o for o in self.held if o not in self.touch]:
            del self.held[o]
        for o, v in self.held.items():
            self.seen[o] = (v, self.shift)
        self.ub_next = rest
        spent["t_valid"] = perf_counter() - objects_done
        return self._result(), {"outcome": "validated" if evaluated else "empty", "opq_validation": evaluated, "opq_total": evaluated + self.m, "reused": reused} | spent
