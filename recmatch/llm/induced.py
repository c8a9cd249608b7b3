"""External induced suffix sorting of many byte strings, with common-prefix values, in numpy blocks.

A suffix is L if its first differing neighbour to the right is smaller, else S; the S suffixes with an L
one before them are the seeds. Seeds are sorted by recursion on the string of their substrings' names;
all others are induced: suffixes leave a priority queue in order, and each pushes the suffix one to its
left, keyed by that suffix's first symbol. A queue is a list of buckets of the key's range; a bucket
keeps what was pushed in order, so first in first out settles ties, and writes it out as runs once the
queue's memory is used up. Popping a bucket reads its runs back in order.

The tuples that move are (symbol, position, common prefix with the queue's previous tuple of that symbol).
The common prefix of two suffixes pushed to one symbol is one more than the least between their sources,
so it is carried through both passes; seeds get theirs from fingerprints.

Every string ends in an end mark of its own, less than any symbol, so suffixes never compare across strings.
"""

from __future__ import annotations

import io
import uuid

import numpy as np

#: Odd multipliers of fingerprints modulo 2**64.
BASE, MIX = 0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9
RECENT = 1 << 15


class Spill:
    """Where runs go: a folder of a pyarrow file system, or memory files if there is none. A file holds a run of each bucket, side by side."""

    def __init__(self, fs=None, folder: str | None = None, budget: int = 256 << 20):
        self.fs, self.folder, self.budget, self.used, self.written = fs, folder, budget, 0, 0
        self.memory: dict[str, bytes] = {}

    def write(self, runs: list[list[np.ndarray]]) -> tuple[str, list[tuple[int, int]]]:
        """The file's name, and where in it each run lies."""
        out, spots = io.BytesIO(), []
        for arrays in runs:
            at = out.tell()
            for a in arrays:
                np.save(out, a, allow_pickle=False)
            spots.append((at, out.tell() - at))
        name = uuid.uuid4().hex
        self.written += out.tell()
        if self.fs is None:
            self.memory[name] = out.getvalue()
        else:
            self.fs.create_dir(self.folder)
            with self.fs.open_output_stream(f"{self.folder}/{name}") as f:
                f.write(out.getbuffer())
        return name, spots

    def read(self, name: str, at: int, size: int, n: int) -> list[np.ndarray]:
        if self.fs is None:
            data = self.memory[name][at : at + size]
        else:
            with self.fs.open_input_file(f"{self.folder}/{name}") as f:
                f.seek(at)
                data = f.read(size)
        src = io.BytesIO(data)
        return [np.load(src, allow_pickle=False) for _ in range(n)]

    def drop(self, name: str) -> None:
        if self.fs is None:
            del self.memory[name]
        else:
            self.fs.delete_file(f"{self.folder}/{name}")


class Run(tuple):
    """Where a bucket's run lies: file, first byte, size."""


class Queue:
    """A monotone priority queue of tuples over keys 0 to `keys` - 1, in blocks."""

    def __init__(self, keys: int, width: int, spill: Spill, columns: int):
        self.width, self.spill, self.columns = width, spill, columns
        self.buckets: list[list] = [[] for _ in range(-(-keys // width))]
        self.recent: list[tuple] = []
        self.held = self.n_recent = 0
        self.left: dict[str, int] = {}

    def push(self, *columns: np.ndarray) -> None:
        """Tuples, key first, in the order they were made. Small pushes wait together, to be dealt out at once."""
        n = len(columns[0])
        if not n:
            return
        self.recent.append(columns)
        self.n_recent += n
        size = sum(c.nbytes for c in columns)
        self.held += size
        self.spill.used += size
        if self.n_recent > RECENT or self.spill.used > self.spill.budget:
            self.deal()
        if self.spill.used > self.spill.budget:
            self.flush()

    def deal(self) -> None:
        columns = [np.concatenate(c) for c in zip(*self.recent)]
        self.recent, self.n_recent = [], 0
        b = columns[0] // self.width if self.width > 1 else columns[0]
        order = np.argsort(b.astype(np.uint16) if len(self.buckets) < 2**16 else b, kind="stable")
        b, columns = b[order], [c[order] for c in columns]
        cuts = np.flatnonzero(np.concatenate([[True], b[1:] != b[:-1]])).tolist()
        buckets = self.buckets
        for k, i, j in zip(b[cuts].tolist(), cuts, [*cuts[1:], len(b)]):
            buckets[k].append([c[i:j] for c in columns])

    def flush(self) -> None:
        """What the buckets hold becomes one file; a bucket's earlier runs stay before the new one."""
        full = [k for k, bucket in enumerate(self.buckets) if any(not isinstance(p, Run) for p in bucket)]
        if full:
            name, spots = self.spill.write([[np.concatenate(c) for c in zip(*(p for p in self.buckets[k] if not isinstance(p, Run)))] for k in full])
            for k, spot in zip(full, spots):
                self.buckets[k] = [*(p for p in self.buckets[k] if isinstance(p, Run)), Run((name, *spot))]
            self.left[name] = len(full)
        self.spill.used -= self.held
        self.held = 0

    def _read(self, run: Run) -> list[np.ndarray]:
        got = self.spill.read(*run, self.columns)
        self.left[run[0]] -= 1
        if not self.left[run[0]]:
            self.spill.drop(run[0])
        return got

    def pop(self, b: int) -> list[np.ndarray] | None:
        bucket, self.buckets[b] = self.buckets[b], []
        parts = [self._read(p) if isinstance(p, Run) else p for p in bucket]
        freed = sum(x.nbytes for p, q in zip(parts, bucket) if not isinstance(q, Run) for x in p)
        if self.recent:
            columns = [np.concatenate(c) for c in zip(*self.recent)] if len(self.recent) > 1 else list(self.recent[0])
            own = columns[0] < (b + 1) * self.width  # nothing below this bucket is left
            if own.any():
                parts.append([c[own] for c in columns])
                freed += sum(x.nbytes for x in parts[-1])
                columns = [c[~own] for c in columns]
            self.recent, self.n_recent = [tuple(columns)], len(columns[0])
        self.held -= freed
        self.spill.used -= freed
        return [np.concatenate(c) for c in zip(*parts)] if parts else None


def kinds(t: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(S type, seed, length of the run of equal symbols) of each position; end marks are 0."""
    n = len(t)
    change = np.ones(n, bool)
    change[:-1] = (t[:-1] != t[1:]) | (t[:-1] == 0)
    last = np.flatnonzero(change)
    end = np.repeat(last, np.diff(last, prepend=-1))
    s = np.ones(n, bool)
    inner = end < n - 1
    s[inner] = t[end[inner]] < t[end[inner] + 1]
    s[t == 0] = True
    seed = np.zeros(n, bool)
    seed[1:] = s[1:] & ~s[:-1]
    seed[t == 0] = True
    return s, seed, (end - np.arange(n) + 1).astype(np.int32)


def _least(lcp: np.ndarray, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """min(lcp[a:b]) of many ranges, a < b, by a sparse table."""
    n = b - a
    level = np.zeros(len(n), np.int64)
    np.log2(n, out=(f := np.empty(len(n)))) if len(n) else None
    if len(n):
        level = f.astype(np.int64)
    out = np.empty(len(n), lcp.dtype)
    table, k = lcp, 0
    while True:
        at = np.flatnonzero(level == k)
        if len(at):
            out[at] = np.minimum(table[a[at]], table[b[at] - (1 << k)])
        k += 1
        if not len(n) or k > level.max():
            return out
        half = 1 << (k - 1)
        table = np.minimum(table[:-half], table[half:])


def sweep(t: np.ndarray, wanted: np.ndarray, first: np.ndarray, seeds: np.ndarray, keys: int, spill: Spill, lcp: np.ndarray | None = None, run: np.ndarray | None = None, most: int = 0):
    """One induction pass.

    t: keys in the pass's direction; wanted: which positions it induces; first: which positions start a string;
    seeds: positions in order, that follow the induced ones of their key. Returns positions, keys and, if
    lcp (of neighbouring seeds) is given, common prefixes of neighbouring induced suffixes up to `most`.
    """
    carried = lcp is not None
    width = 1 if keys <= 1024 else max(1, int(keys / max(1.0, len(t) ** 0.5)))
    q = Queue(keys, width, spill, 3 if carried else 2)
    out_p, out_l = [], []
    seed_keys = t[seeds]
    cuts = np.searchsorted(seed_keys, np.arange(0, keys + width, width))
    carry = np.zeros(keys, np.int32)

    def pushed(src: np.ndarray, lc: np.ndarray | None):
        """What the sources push, and the common prefixes with the last push of the same key."""
        ok = ~first[src]
        ok[ok] = wanted[src[ok] - 1]
        at = np.flatnonzero(ok)
        p = src[at] - 1
        k = t[p]
        if lc is None:
            return k, p, None
        order = np.argsort(k.astype(np.uint16), kind="stable")
        i, kk = at[order], k[order]
        head = np.ones(len(i), bool)
        head[1:] = kk[1:] != kk[:-1]
        down = np.minimum.accumulate(lc)
        val = np.empty(len(i), np.int32)
        val[head] = np.minimum(carry[kk[head]], down[i[head]])
        rest = np.flatnonzero(~head)
        val[rest] = _least(lc, i[rest - 1] + 1, i[rest] + 1)
        np.minimum(carry, down[-1] if len(lc) else carry, out=carry)
        tail = np.ones(len(i), bool)
        tail[:-1] = head[1:]
        up = np.minimum.accumulate(np.append(lc, most)[::-1])[::-1]
        carry[kk[tail]] = up[i[tail] + 1]
        back = np.empty(len(i), np.int32)
        back[order] = np.minimum(val + 1, most)
        return k, p, back

    for b in range(len(q.buckets)):
        got = q.pop(b)
        s0, s1 = cuts[b], cuts[b + 1]
        if got is None and s0 == s1:
            continue
        if width == 1:
            last = None
            fresh = True
            while got is not None and len(got[0]):
                p = got[1]
                lc = got[2] if carried else None
                if carried and fresh:
                    lc = lc.copy()
                    lc[0] = 0
                fresh = False
                out_p.append(p)
                if carried:
                    out_l.append(lc)
                last = p[-1]
                k, new, lc = pushed(p, lc)
                here = k == b
                there = ~here
                q.push(k[there], new[there], *([lc[there]] if carried else []))
                got = [k[here], new[here], *([lc[here]] if carried else [])]
            if s1 > s0:
                lc = None
                if carried:
                    lc = lcp[s0:s1].copy()
                    lc[0] = 0 if last is None else min(run[last], run[seeds[s0]], most)
                k, new, lc = pushed(seeds[s0:s1], lc)
                q.push(k, new, *([lc] if carried else []))
            continue
        high = (b + 1) * width
        k, p = got if got is not None else (np.zeros(0, t.dtype), np.zeros(0, np.int32))
        order = np.argsort(k, kind="stable")
        k, p = k[order], p[order]
        sk, sp = seed_keys[s0:s1], seeds[s0:s1]
        while len(k) or len(sk):
            both = np.concatenate([2 * k, 2 * sk + 1])
            src = np.concatenate([p, sp])
            order = np.argsort(both, kind="stable")
            both, src = both[order], src[order]
            nk, np_, _ = pushed(src, None)
            here = nk < high
            least = nk[here].min() if here.any() else None
            n = len(both) if least is None else int(np.searchsorted(both, 2 * least, "right"))
            if n < len(both):  # only what precedes the least new key is in its final order
                nk, np_, _ = pushed(src[:n], None)
                here = nk < high
            out_p.append(src[:n][both[:n] % 2 == 0])
            q.push(nk[~here], np_[~here])
            lk, ls = both[n:], src[n:]
            odd = lk % 2 == 1
            sk, sp = lk[odd] // 2, ls[odd]
            k, p = np.concatenate([lk[~odd] // 2, nk[here]]), np.concatenate([ls[~odd], np_[here]])
            order = np.argsort(k, kind="stable")
            k, p = k[order], p[order]
    pos = np.concatenate(out_p) if out_p else np.zeros(0, np.int32)
    return pos, (np.concatenate(out_l) if out_l else np.zeros(0, np.int32)) if carried else None


def _first(t: np.ndarray) -> np.ndarray:
    first = np.zeros(len(t), bool)
    first[0] = True
    first[1:] = t[:-1] == 0
    return first


def _both(t, s, first, seeds, spill, lcp=None, run=None, most=0):
    """L pass upwards, then S pass downwards: (L positions, their lcp, S positions downwards, their lcp)."""
    keys = int(t.max()) + 1
    a, la = sweep(t, ~s & (t > 0), first, seeds, keys, spill, lcp, run, most)
    down = keys - 1 - t
    back = None
    if lcp is not None:  # neighbours downwards: the value stands with the upper one
        back = np.append(la[1:], 0)[::-1].astype(np.int32) if len(la) else la
    z, lz = sweep(down, s & (t > 0), first, a[::-1], keys, spill, back, run, most)
    return a, la, z, lz


def seed_order(t: np.ndarray, s: np.ndarray, seed: np.ndarray, first: np.ndarray, spill: Spill) -> np.ndarray:
    """Seeds in the order of their suffixes: end marks by place, then by recursion on names."""
    places = np.flatnonzero(seed).astype(np.int32)
    marks = places[t[places] == 0]
    inner = places[t[places] > 0]
    if not len(inner):
        return marks
    rough = inner[np.argsort(t[inner], kind="stable")]
    _, _, z, _ = _both(t, s, first, np.concatenate([marks, rough]), spill)
    by = z[::-1]
    by = by[seed[by]]  # seeds by their substrings, a substring reaching to the next seed
    rank = np.cumsum(seed, dtype=np.int32)  # one more than a seed's place among seeds
    after = places[rank[by]]
    sym = (2 * t + s).astype(np.uint64) + np.uint64(1)
    n = after - by + 1
    with np.errstate(over="ignore"):
        up = np.full(int(n.max()), BASE, np.uint64)
        up[0] = 1
        up = np.cumprod(up)
        flat = np.repeat(by - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(int(n.sum()))
        off = flat - np.repeat(by, n)
        prints = np.add.reduceat(sym[flat] * np.uint64(MIX) * up[off], np.concatenate([[0], np.cumsum(n)[:-1]]))
    new = np.ones(len(by), bool)
    new[1:] = (prints[1:] != prints[:-1]) | (n[1:] != n[:-1]) | (t[after[1:]] == 0)
    name = np.cumsum(new)
    if name[-1] == len(by):
        return np.concatenate([marks, by])
    short = np.zeros(len(places), np.int32)
    short[rank[by] - 1] = name
    return np.concatenate([marks, places[order_of(short, spill)]])


def order_of(t: np.ndarray, spill: Spill) -> np.ndarray:
    """Positions of all suffixes but end marks, in order."""
    s, seed, run = kinds(t)
    first = _first(t)
    a, _, z, _ = _both(t, s, first, seed_order(t, s, seed, first, spill), spill)
    return _merged(t, a, z[::-1])


def _merged(t, a, z):
    pos = np.concatenate([a, z])
    return pos[np.argsort(t[pos], kind="stable")]


def prefix_of(prints: np.ndarray, down: np.ndarray, left: np.ndarray, a: np.ndarray, b: np.ndarray, most: int) -> np.ndarray:
    """Common prefixes of suffix pairs up to `most`, by bisection on fingerprints; left: symbols to the string's end."""
    high = np.minimum(np.minimum(left[a], left[b]), most).astype(np.int32)
    low = np.zeros(len(a), np.int32)
    with np.errstate(over="ignore"):
        at_a, at_b, scale = prints[a], prints[b], down[b] * up_of(down, a)
        todo, ask = np.arange(len(a)), 16  # most pairs part early, so the first question is a short prefix
        todo = todo[high > 0]
        while len(todo):
            lo, hi = low[todo], high[todo]
            mid = np.minimum((lo + hi + 1) // 2, ask) if ask else (lo + hi + 1) // 2
            ask = 0
            same = (prints[a[todo] + mid] - at_a[todo]) == (prints[b[todo] + mid] - at_b[todo]) * scale[todo]
            low[todo], high[todo] = np.where(same, mid, lo), np.where(same, hi, mid - 1)
            todo = todo[low[todo] < high[todo]]
    return low


def up_of(down: np.ndarray, a: np.ndarray) -> np.ndarray:
    """Inverses modulo 2**64 of odd numbers, by Newton's steps."""
    x = down[a]
    y = x.copy()
    for _ in range(5):
        y *= np.uint64(2) - x * y
    return y


def repeated(strings: list[bytes], most: int, spill: Spill | None = None, copies: list[bool] | None = None, marks: list[int] | None = None) -> list[np.ndarray]:
    """Per string, which of its positions start `most` bytes that another string or place has too.

    copies: which strings stand for several equal ones. Their suffixes would be neighbours with all they have in common.
    marks: a position of each string whose byte counts as a symbol beyond all bytes.
    """
    spill = spill or Spill()
    size = np.array([len(x) for x in strings], np.int64)
    at = np.concatenate([[0], np.cumsum(size + 1)])
    t = np.zeros(int(at[-1]), np.int32)
    raw = np.frombuffer(b"\0".join(strings) + b"\0", np.uint8)
    t[:] = raw
    t += 1
    t[at[1:] - 1] = 0
    if marks is not None:
        t[at[:-1] + np.array(marks, np.int64)] = 257
    s, seed, run = kinds(t)
    first = _first(t)
    seeds = seed_order(t, s, seed, first, spill)
    left = (np.repeat(at[1:] - 1, size + 1) - np.arange(len(t))).astype(np.int32)
    with np.errstate(over="ignore"):
        up, down = np.full(len(t) + 1, BASE, np.uint64), np.full(len(t) + 1, pow(BASE, -1, 2**64), np.uint64)
        up[0] = down[0] = 1
        up, down = np.cumprod(up), np.cumprod(down)
        mixed = (t.astype(np.uint64) + np.uint64(1)) * np.uint64(MIX)
        mixed ^= mixed >> np.uint64(29)
        prints = np.zeros(len(t) + 1, np.uint64)
        np.cumsum(mixed * up[:-1], out=prints[1:])
    lcp = np.zeros(len(seeds), np.int32)
    lcp[1:] = prefix_of(prints, down, left, seeds[:-1], seeds[1:], most)
    a, la, z, lz = _both(t, s, first, seeds, spill, lcp, np.minimum(run, most).astype(np.int32), most)
    twice = np.zeros(len(t), bool)
    for pos, common in ((a, la), (z, lz)):
        hit = np.flatnonzero(common >= most)
        twice[pos[hit]] = True
        twice[pos[hit - 1]] = True
    if copies is not None:
        twice |= np.repeat(np.array(copies, bool), size + 1) & (left >= most)
    # Where a symbol's L suffixes meet its S ones, they share its run.
    long = np.flatnonzero(run >= most)
    if len(long):
        for c in np.unique(t[long]):
            own = long[t[long] == c]
            if (~s[own]).any() and s[own].any():
                for group in (own[~s[own]], own[s[own]]):
                    twice[group[np.argmax(run[group])]] = True
    return np.split(twice[t > 0], np.cumsum(size)[:-1])
