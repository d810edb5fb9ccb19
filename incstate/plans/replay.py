"""Edit logs of many small circuits replayed together, the same method as :class:`~incstate.plans.small.SmallCircuit`.

All circuits of a batch take their k-th edit and their k-th affected slot at once, in arrays, so that Python's work
grows with the longest log of a batch and not with the number of circuits.  Every slot that a log ever makes has a
lifetime in iterations; an update walks the slots from the first one that came or went, and computes only the
blocks that are affected.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from incstate.functions.gates import TOLERANCE, base_kind, matrix
from incstate.operators.partition import log2, pattern

#: Amplitudes of block versions that one batch of circuits holds.
BATCH_AMPLITUDES = 1 << 21
#: Edits that are read before circuits are replayed.
CHUNK_EDITS = 1 << 17
COUNTS = ("frontier_parts", "affected_parts", "span_amplitudes", "written_blocks", "total_blocks")

Measure = Callable[[np.ndarray], dict[str, np.ndarray]]


NONE = np.iinfo(np.int64).min


def _whole(column, empty: int = 0) -> np.ndarray:
    return pc.fill_null(column, empty).to_numpy(zero_copy_only=False).astype(np.int64)


def _flat(column):
    return column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column


def _matrices(kinds: list[str], code: np.ndarray, theta: np.ndarray) -> np.ndarray:
    """The 2x2 matrix of every gate; angles are NaN where there is none."""
    u = np.zeros((len(code), 2, 2), complex)
    half = theta / 2
    c, s = (np.where(np.abs(v) < TOLERANCE, 0.0, v) for v in (np.cos(half), np.sin(half)))
    for k, kind in enumerate(kinds):
        on, base = np.flatnonzero(code == k), base_kind(kind)
        if kind == "SWAP":
            continue
        if base not in ("RX", "RY", "RZ"):
            u[on] = matrix(kind)
            continue
        if np.isnan(theta[on]).any():
            raise ValueError(f"{kind} needs an angle")
        x, y = c[on], s[on]
        u[on, 0, 0], u[on, 1, 1] = (x - 1j * y, x + 1j * y) if base == "RZ" else (x, x)
        if base != "RZ":
            u[on, 0, 1], u[on, 1, 0] = (-1j * y, -1j * y) if base == "RX" else (-y, y)
    return u


_ID, _MIX, _OTHER = 0, 1, 2


def _forms(u: np.ndarray, swap: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """What each gate does (nothing, mixing, else), and a number that tells shapes apart."""
    size = np.abs(u)
    straight = (size[:, 0, 1] < TOLERANCE) & (size[:, 1, 0] < TOLERANCE)
    crossed = (size[:, 0, 0] < TOLERANCE) & (size[:, 1, 1] < TOLERANCE)
    ones = [np.abs(u[:, i, i] - 1) < TOLERANCE for i in (0, 1)]
    shape = np.select([swap, straight & ones[0] & ones[1], straight & ones[0], straight, crossed], [5, 0, 2, 3, 4], 1)
    return np.where(shape == 0, _ID, np.where(shape == 1, _MIX, _OTHER)), shape


class Batch:
    """Flat logs of whole circuits, sorted by circuit and order; ``first`` has each circuit's first row."""

    def __init__(self, log: pa.Table, n: int, block_size: int, sync: str):
        self.n, self.b, self.sync = n, log2(block_size, n), sync
        self.n_blocks, self.size = 1 << (n - self.b), 1 << n
        circuit = _whole(log["circuit_id"], NONE)
        self.first = np.concatenate(([0], np.flatnonzero(np.diff(circuit)) + 1)) if len(circuit) else np.zeros(0, np.int64)
        self.ids = circuit[self.first]
        self.of = np.repeat(np.arange(len(self.first)), np.diff(np.append(self.first, len(circuit))))
        self.iter, self.net, self.number = (_whole(log[c]) for c in ("iter", "net_no", "gate_no"))
        change = np.concatenate(([True], (np.diff(self.iter) != 0) | (np.diff(circuit) != 0)))[: len(circuit)]
        step = np.cumsum(change) - 1
        self.at = step - step[self.first][self.of]
        self.updates = np.maximum.reduceat(self.at, self.first) + 1
        self.names = self.iter[change]
        self._gates(log)
        self._lives()
        self._slots()

    def _gates(self, log: pa.Table) -> None:
        op = pc.dictionary_encode(_flat(log["op"]))
        ops = op.dictionary.to_pylist()
        self.insert, self.remove = (np.isin(_whole(op.indices, -1), [k for k, x in enumerate(ops) if x == name]) for name in ("insert", "remove"))
        kind = pc.dictionary_encode(_flat(log["kind"]))
        kinds = [x or "" for x in kind.dictionary.to_pylist()]
        code = np.where(self.insert, _whole(kind.indices, -1), -1)
        if (code[self.insert] < 0).any():
            raise ValueError("unknown gate kind None")
        theta = pc.fill_null(log["theta"], float("nan")).to_numpy(zero_copy_only=False).astype(float)
        self.target = _whole(log["target"])
        controls = _flat(log["controls"])
        count = _whole(pc.list_value_length(controls))
        flat, owner = _whole(controls.flatten()), np.repeat(np.arange(len(code)), count)
        self.held = np.zeros(len(code), np.int64)
        np.bitwise_or.at(self.held, owner, np.left_shift(1, flat))
        self.mask = self.held | np.left_shift(1, self.target)
        swap = np.isin(code, [k for k, x in enumerate(kinds) if x == "SWAP"])
        self.other = np.full(len(code), -1)
        start = np.cumsum(count) - count
        self.other[swap] = flat[start[swap]]
        self.held[swap] &= ~np.left_shift(1, self.other[swap])
        used = [k if (code == k).any() else None for k in range(len(kinds))]
        self.u = _matrices([kinds[k] if k is not None else "X" for k in used], code, theta)
        self.form, shape = _forms(self.u, swap)
        # Gates of one shape on the same qubits have one pattern; gates that are equal in all share a code.
        place = ((self.held * 64 + self.other + 1) * 64 + self.target) * 8 + shape
        _, rep, self.pattern = np.unique(place, return_index=True, return_inverse=True)
        self.code, self.theta = code, np.nan_to_num(theta)
        k = np.arange(self.n_blocks)
        self.lo, self.hi = np.zeros((len(rep), self.n_blocks), np.int64), np.full((len(rep), self.n_blocks), -1)
        self.width = np.zeros(len(rep), np.int64)
        for row, r in enumerate(rep.tolist()):
            if not self.insert[r] or self.form[r] == _ID:
                alike = np.flatnonzero((self.pattern == row) & self.insert & (self.form != _ID))
                if not len(alike):
                    continue
                r = int(alike[0])
            made = pattern(kinds[code[r]], int(self.target[r]), tuple(flat[start[r] : start[r] + count[r]].tolist()), float(theta[r]), self.n, self.b)
            for part in range(made.count):
                lo, hi = made.bounds(part, self.b)
                self.lo[row, lo : hi + 1], self.hi[row, lo : hi + 1] = lo, hi
                if not part:
                    self.width[row] = hi - lo
        self.writes = self.hi >= 0
        self.opens = self.writes & (self.lo == k)

    def _lives(self) -> None:
        """Iterations in which each inserted gate lives: an insert that meets a qubit of its net in use is refused."""
        rows = len(self.of)
        (net, nets), (gate, gates) = (_within(self.of, x) for x in (self.net, self.number))
        never = self.updates[self.of]
        self.born, self.died = np.full(rows, -1), never.copy()
        used, live, dead = np.zeros(nets, np.int64), np.full(gates, -1), np.full(gates, -1)
        order = np.arange(rows) - self.first[self.of]
        by_turn = np.argsort(order, kind="stable")
        cuts = np.searchsorted(order[by_turn], np.arange(order.max(initial=-1) + 2))

        def end(held: np.ndarray, now: np.ndarray) -> None:
            used[net[held]] &= ~self.mask[held]
            self.died[held] = now

        for a, z in zip(cuts, cuts[1:]):
            r = by_turn[a:z]
            gone = r[self.remove[r]]
            gone = gone[live[gate[gone]] >= 0]
            if len(gone):
                held = live[gate[gone]]
                end(held, self.at[gone])
                live[gate[gone]], dead[gate[gone]] = -1, held
            new = r[self.insert[r]]
            new = new[(used[net[new]] & self.mask[new]) == 0]
            old = live[gate[new]]
            end(old[old >= 0], self.at[new[old >= 0]])
            last = dead[gate[new]]
            # Taken out and put back as it was before the next update: nothing changed.
            same = (last >= 0) & (old < 0) & (self.died[last] == self.at[new])
            for x in (net, self.code, self.target, self.held, self.other, self.theta):
                same &= x[last] == x[new]
            self.died[last[same]] = never[last[same]]
            self.born[new[~same]] = self.at[new[~same]]
            now = np.where(same, last, new)
            live[gate[new]] = now
            used[net[new]] |= self.mask[new]
        self.net_of = net

    def _slots(self) -> None:
        """Every slot of the log with its place, lifetime, gates and pattern, as arrays by circuit and place."""
        lives = (self.born >= 0) & (self.born < self.died)
        mono = np.flatnonzero(lives & (self.form == _OTHER))
        mix = np.flatnonzero(lives & (self.form == _MIX))
        # A net's mixing gates are one slot, another one whenever a gate of them comes or goes.
        far = int(self.updates.max(initial=0)) + 1
        times = np.unique(np.concatenate([self.net_of[mix] * far + self.born[mix], self.net_of[mix] * far + self.died[mix]]))
        a, z = (np.searchsorted(times, self.net_of[mix] * far + x[mix]) for x in (self.born, self.died))
        span, gate = _ranges(a, z - a), np.repeat(mix, z - a)
        order = np.lexsort((self.number[gate], span))
        span, gate = span[order], gate[order]
        shared, start, count = np.unique(span, return_index=True, return_counts=True)
        most = int(count.max(initial=1))
        members = np.full((len(shared) + len(mono), most), -1)
        nth = np.arange(len(span)) - np.repeat(start, count)
        members[np.repeat(np.arange(len(shared)), count), nth] = gate
        members[len(shared) :, 0] = mono
        lead = members[:, 0]
        sup = np.arange(len(members)) < len(shared)
        born = np.concatenate([times[shared] % far, self.born[mono]])
        died = np.concatenate([times[np.minimum(shared + 1, max(len(times) - 1, 0))] % far, self.died[mono]])
        tail = np.where(members >= 0, self.number[members], np.iinfo(np.int64).min)
        zero = np.zeros(len(members), np.int64)
        keys = [self.of[lead], self.net[lead], ~sup, np.where(sup, zero, self.width[self.pattern[lead]]), *tail.T, born]
        order = np.lexsort(keys[::-1])
        self.members, self.sup, lead = members[order], sup[order], lead[order]
        born, died = born[order], died[order]
        circuit = self.of[lead]
        held = np.bincount(circuit, minlength=len(self.first))
        place = np.arange(len(order)) - np.repeat(np.cumsum(held) - held, held)
        self.slots = np.full((len(self.first), max(1, int(held.max(initial=0)))), -1)
        self.slots[circuit, place] = np.arange(len(order))
        self.slot_born, self.slot_died = np.full(self.slots.shape, far + 1), np.full(self.slots.shape, -1)
        self.slot_born[circuit, place], self.slot_died[circuit, place] = born, died
        self.slot_pattern = self.pattern[lead]
        self.written = np.zeros((*self.slots.shape, self.n_blocks), bool)
        self.written[circuit, place] = self.writes[self.slot_pattern]
        coupled = np.where(self.members >= 0, np.left_shift(1, self.target[self.members]) >> self.b, 0)
        self.coupled = np.bitwise_or.reduce(coupled, axis=1) if len(coupled) else np.zeros(0, np.int64)

    def _apply(self, work: np.ndarray, row: np.ndarray, block: np.ndarray, gate: np.ndarray) -> None:
        """One gate on blocks of rows of ``work``; ``gate`` is that of each block's row."""
        i = (block << self.b)[:, None] + np.arange(1 << self.b)
        t, held, other, u, row = self.target[gate][:, None], self.held[gate][:, None], self.other[gate][:, None], self.u[gate], row[:, None]
        x = work[row, i]
        ok = (i & held) == held
        swap = other >= 0
        flip = np.left_shift(1, t)
        source = i ^ flip
        if swap.any():
            o = np.maximum(other, 0)
            source = np.where(swap, np.where(((i >> t) ^ (i >> o)) & 1 == 1, i ^ (flip | np.left_shift(1, o)), i), source)
        y = work[row, source]
        bit = (i & flip) != 0
        made = np.where(bit, u[:, 1, 1, None], u[:, 0, 0, None]) * x + np.where(bit, u[:, 1, 0, None], u[:, 0, 1, None]) * y
        if swap.any():
            made = np.where(swap, y, made)
        work[row, i] = np.where(ok, made, x)

    def run(self) -> Iterator[tuple[np.ndarray, np.ndarray, dict[str, np.ndarray], np.ndarray]]:
        """After every update: the circuits that had one, its name, its counts and the states."""
        circuits, places = self.slots.shape
        blocks = self.n_blocks
        versions = np.zeros((circuits, places, self.size), complex)
        state = np.zeros((circuits, self.size), complex)
        state[:, 0] = 1
        named = np.cumsum(self.updates) - self.updates
        where = np.arange(places)
        for t in range(int(self.updates.max(initial=0))):
            on = np.flatnonzero(self.updates > t)
            born, died = self.slot_born[on], self.slot_died[on]
            alive = (born <= t) & (died > t)
            new, gone = born == t, died == t
            moved = new | gone
            begin = np.where(moved.any(axis=1), moved.argmax(axis=1), places)
            behind = where >= begin[:, None]
            # Where anything but new slots follows, the state before the first change comes from versions.
            back = np.flatnonzero((behind & (alive | gone) & ~new).any(axis=1))
            if len(back):
                c = on[back]
                ahead = (alive[back] & ~behind[back])[:, :, None] & self.written[c]
                last = np.where(ahead.any(axis=1), places - 1 - ahead[:, ::-1].argmax(axis=1), -1)
                held = versions.reshape(circuits, places, blocks, -1)[c[:, None], np.maximum(last, 0), np.arange(blocks)]
                held[last < 0] = 0
                held[last[:, 0] < 0, 0, 0] = 1
                state[c] = held.reshape(len(c), -1)
            at, place = np.nonzero(behind & (alive | gone))
            turn = np.arange(len(at)) - np.searchsorted(at, at)
            by_turn = np.argsort(turn, kind="stable")
            cuts = np.searchsorted(turn[by_turn], np.arange(turn.max(initial=-1) + 2))
            dirty, removed, spanned = (np.zeros((len(on), blocks), bool) for _ in range(3))
            count = {k: np.zeros(len(on), np.int64) for k in COUNTS}
            for a, z in zip(cuts, cuts[1:]):
                r = by_turn[a:z]
                x, s = at[r], place[r]
                out = gone[x, s]
                if out.any():
                    removed[x[out]] |= self.written[on[x[out]], s[out]]
                    x, s = x[~out], s[~out]
                    if not len(x):
                        continue
                self._visit(on[x], s, x, new[x, s], state, versions, dirty, removed, spanned, count)
            count["span_amplitudes"] = spanned.sum(axis=1) << self.b
            count["total_blocks"] = alive.sum(axis=1) * blocks
            yield self.ids[on], self.names[named[on] + t], count, state[on]

    def _visit(self, c, s, x, new, state, versions, dirty, removed, spanned, count) -> None:
        """Slots ``s`` of circuits ``c``, one each: ``x`` are the circuits' rows of what this update keeps."""
        slot = self.slots[c, s]
        sup, look, writes = self.sup[slot], self.slot_pattern[slot], self.written[c, s]
        if new.all():
            hit = fresh = writes
        else:
            lost = removed[x]
            open_ = dirty[x] | lost
            hit, fresh = (self._met(look, m) for m in (open_, lost))
            wide = np.flatnonzero(sup)
            if len(wide):
                fresh[wide] = lost[wide].any(axis=1)[:, None]
                if self.sync == "global":
                    hit[wide] = open_[wide].any(axis=1)[:, None]
                else:
                    hit[wide] = self._coupled(open_[wide], self.coupled[slot[wide]])
            fresh &= hit
            hit[new], fresh[new] = writes[new], writes[new]
        opens = self.opens[look]
        count["affected_parts"][x] += (hit & opens).sum(axis=1)
        count["frontier_parts"][x] += (fresh & opens).sum(axis=1)
        count["written_blocks"][x] += hit.sum(axis=1)
        work = state[c]
        row, block = np.nonzero(hit)
        members = self.members[slot]
        for g in range(members.shape[1]):
            gate = members[row, g]
            some = gate >= 0
            if some.all():
                self._apply(work, row, block, gate)
            elif some.any():
                self._apply(work, row[some], block[some], gate[some])
            else:
                break
        if new.all():
            versions[c, s] = work
            state[c] = work
        else:
            cut = (len(c), self.n_blocks, -1)
            made = np.where(hit[:, :, None], work.reshape(cut), versions[c, s].reshape(cut))
            versions[c, s] = made.reshape(len(c), -1)
            state[c] = np.where(writes[:, :, None], made, work.reshape(cut)).reshape(len(c), -1)
        dirty[x] |= hit
        removed[x] &= ~hit
        spanned[x] |= hit

    def _met(self, look: np.ndarray, marked: np.ndarray) -> np.ndarray:
        """Blocks of the partitions that hold a marked block."""
        total = np.zeros((len(marked), self.n_blocks + 1), np.int64)
        np.cumsum(marked, axis=1, out=total[:, 1:])
        row = np.arange(len(marked))[:, None]
        return total[row, self.hi[look] + 1] > total[row, self.lo[look]]

    def _coupled(self, marked: np.ndarray, mask: np.ndarray) -> np.ndarray:
        k, out = np.arange(self.n_blocks), marked.copy()
        for q in range(self.n - self.b):
            on = (mask >> q & 1) == 1
            out[on] |= out[on][:, k ^ (1 << q)]
        return out


def _within(circuit: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, int]:
    """Numbers that tell ``x`` apart within each circuit, and a bound on them."""
    if not len(x):
        return x, 0
    low, high = int(x.min()), int(x.max())
    wide = high - low + 1
    if wide * (int(circuit.max()) + 1) > 8 * len(x) + 1024:
        values, x = np.unique(x, return_inverse=True)
        low, wide = 0, len(values)
    code = circuit * wide + (x - low)
    if wide * (int(circuit.max()) + 1) <= 8 * len(x) + 1024:
        return code, wide * (int(circuit.max()) + 1)
    return np.unique(code, return_inverse=True)[1], len(x)


def _ranges(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The numbers from each start, ``count`` of them, one after another."""
    return np.repeat(start - (np.cumsum(count) - count), count) + np.arange(count.sum())


def whole_circuits(batches: Iterator[pa.RecordBatch], least: int = CHUNK_EDITS) -> Iterator[pa.Table]:
    """Rows sorted by circuit, cut between circuits into tables of about ``least`` rows."""
    held: list[pa.RecordBatch] = []
    have = 0
    for batch in batches:
        held.append(batch)
        have += len(batch)
        # Only the newest rows can end a circuit where the older ones didn't.
        if have < least:
            continue
        table = pa.Table.from_batches(held).combine_chunks()
        cut = np.flatnonzero(np.diff(_whole(table["circuit_id"], NONE)))
        if len(cut):
            at = int(cut[-1]) + 1
            yield table.slice(0, at).combine_chunks()
            rest = table.slice(at).combine_chunks()
            held, have = rest.to_batches(), len(rest)
            least = max(CHUNK_EDITS, 2 * have)
        else:
            least = 2 * have
    if have:
        yield pa.Table.from_batches(held).combine_chunks()


def replay_tables(batches: Iterator[pa.RecordBatch], n: int, block_size: int, sync: str, measure: Measure | None) -> Iterator[pa.RecordBatch]:
    """Logs sorted by circuit and order to a row for every circuit and update."""
    for table in whole_circuits(batches):
        circuit = _whole(table["circuit_id"], NONE)
        first = np.concatenate(([0], np.flatnonzero(np.diff(circuit)) + 1))
        length = np.diff(np.append(first, len(circuit)))
        # Circuits of like length together, so that little of the arrays stays empty.
        order = np.argsort(length, kind="stable")
        at = 0
        while at < len(order):
            room = np.arange(1, len(order) - at + 1) * length[order[at:]] << n
            take = max(1, int(np.searchsorted(room, BATCH_AMPLITUDES, side="right")))
            some = np.sort(order[at : at + take])
            at += take
            batch = Batch(table.take(pa.array(_ranges(first[some], length[some]))), n, block_size, sync)
            for ids, names, count, state in batch.run():
                more = measure(state) if measure else {"re": _lists(state.real), "im": _lists(state.imag)}
                columns = {"circuit_id": pa.array(ids, mask=ids == NONE), "iter": names, **{k: count[k] for k in COUNTS}, **more}
                yield pa.RecordBatch.from_pydict({k: v if isinstance(v, pa.Array) else pa.array(v) for k, v in columns.items()})


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(np.ascontiguousarray(x).ravel()))
