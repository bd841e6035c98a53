"""Edit distances of many pairs of texts at once: bit-parallel columns over blocks of 64 rows, pairs side by side."""

from __future__ import annotations

import bisect

import numpy as np

_ONE, _TOP, _FULL = np.uint64(1), np.uint64(63), np.uint64(0xFFFFFFFFFFFFFFFF)


def _cut(a, b):
    """Both sequences without their common beginning and end."""
    most = min(len(a), len(b))
    if a[:most] == b[:most]:
        return a[most:], b[most:]
    lo, hi = 0, most
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[lo:mid] == b[lo:mid]:
            lo = mid
        else:
            hi = mid
    a, b = a[lo:], b[lo:]
    most = min(len(a), len(b))
    if most and a[-most:] == b[-most:]:
        return a[:-most], b[:-most]
    lo, hi = 0, most
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[len(a) - mid : len(a) - lo] == b[len(b) - mid : len(b) - lo]:
            lo = mid
        else:
            hi = mid
    return (a[:-lo], b[:-lo]) if lo else (a, b)


def edit_distance(a, b, most: int | None = None) -> int:
    """Levenshtein distance of two sequences by bit-parallel columns, after the common ends are cut off.

    If `most` is given, a distance over it may come out larger: only rows that a path of so many edits can take are worked on.
    """
    a, b = _cut(a, b)
    if not a or not b:
        return len(a) + len(b)
    more = len(b) - len(a)
    if most is None:
        most = len(a) + len(b)
    elif abs(more) > most:
        return abs(more)
    above, below, step = (most + more) // 2, (most - more) // 2, max(256, most // 4)
    where: dict = {}
    if len(a) < 4000:
        for i, c in enumerate(a):
            where[c] = where.get(c, 0) | 1 << i
    else:
        for i, c in enumerate(a):
            where.setdefault(c, []).append(i)
        where = {c: _bits_at(places, len(a)) for c, places in where.items()}
    up = down = score = lo = hi = 0
    for at in range(0, len(b), step):
        part = b[at : at + step]
        first, end = max(0, at - above), min(len(a), at + len(part) + below + 1)
        size = end - first
        full, top = (1 << size) - 1, 1 << (size - 1)
        up = (up >> (first - lo)) | (full ^ ((1 << (hi - first)) - 1) if hi > first else full)
        down >>= first - lo
        score += end - hi
        lo, hi = first, end
        of = where if size == len(a) else {c: (where[c] >> lo) & full for c in set(part) if c in where}
        for c in part:
            eq = of.get(c, 0)
            diag = (((eq & up) + up) ^ up) | eq | down
            right = (down | ~(diag | up)) & full
            left = up & diag
            if right & top:
                score += 1
            elif left & top:
                score -= 1
            right = (right << 1 | 1) & full
            left = (left << 1) & full
            up = (left | ~(diag | right)) & full
            down = right & diag
    return score


def _bits_at(places: list[int], size: int) -> int:
    """The number whose bits at `places` are set."""
    bits = np.zeros(size, dtype=bool)
    bits[places] = True
    return int.from_bytes(np.packbits(bits, bitorder="little").tobytes(), "little")


#: Words to pass in either text where they differ, few first.
_STEPS = sorted(((i, j) for i in range(13) for j in range(13) if i or j), key=lambda x: (max(x), sum(x)))


def surely_within(a: str, b: str, most: int) -> bool:
    """Whether going along both texts word by word finds at most `most` edits; if not, there may still be so few."""
    x, y = a.split(" "), b.split(" ")
    n, m = len(x), len(y)
    i = j = cost = 0
    while i < n and j < m:
        if x[i] == y[j]:
            i, j = i + 1, j + 1
            continue
        for di, dj in _STEPS:
            if x[i + di : i + di + 2] == y[j + dj : j + dj + 2] and i + di <= n and j + dj <= m:
                cost += max(sum(map(len, x[i : i + di])) + di, sum(map(len, y[j : j + dj])) + dj)
                i, j = i + di, j + dj
                break
        else:
            return False
        if cost > most:
            return False
    return cost + sum(map(len, x[i:])) + n - i + sum(map(len, y[j:])) + m - j <= most


def _within_by_anchors(a: str, b: str, most: int) -> bool:
    """Whether the edits between words that either text has once, in the same order, are at most `most` in all; if not, there may still be so few."""
    x, y = a.split(" "), b.split(" ")
    of = {}
    for i, w in enumerate(y):
        of[w] = -1 if w in of else i
    seen, again = set(), set()
    for w in x:
        (again if w in seen else seen).add(w)
    pairs = [(i, of[w]) for i, w in enumerate(x) if w not in again and of.get(w, -1) >= 0]
    tails, last, before = [], [], []
    for at, (_, j) in enumerate(pairs):  # the longest rising run
        k = bisect.bisect_left(tails, j)
        before.append(last[k - 1] if k else -1)
        tails[k : k + 1], last[k : k + 1] = [j], [at]
    chain, at = [(len(x), len(y))], last[-1] if last else -1
    while at >= 0:
        chain.append(pairs[at])
        at = before[at]
    cost = i = j = 0
    for p, q in reversed(chain):
        if p > i or q > j:
            u, v = "".join(w + " " for w in x[i:p]), "".join(w + " " for w in y[j:q])
            longer = max(len(u), len(v))
            cost += edit_distance(u, v) if longer < 500 else longer
            if cost > most:
                return False
        i, j = p + 1, q + 1
    return True


def _surely_over(a: str, b: str, most: int) -> bool:
    """Whether the counts of pairs of letters alone show more than `most` edits: an edit changes two pairs of either text."""
    x, y = (np.bincount((p[1:] * np.uint32(31) + p[:-1]) & np.uint32(1023), minlength=1024) for p in (_points(a), _points(b)))
    return int(np.abs(x - y).sum()) > 4 * most


def within(left: list[str], right: list[str], most: list[int], memory: int = 1 << 24) -> np.ndarray:
    """Which pairs are at most `most` edits apart; the work arrays take some `memory` bytes."""
    out = np.zeros(len(left), dtype=bool)
    todo = []
    for i, (a, b, m) in enumerate(zip(left, right, most, strict=True)):
        if abs(len(a) - len(b)) > m:
            continue
        if surely_within(a, b, m):
            out[i] = True
            continue
        a, b = _cut(a, b)
        if max(len(a), len(b)) <= m:
            out[i] = True
        elif len(a) > 1000 and _surely_over(a, b, m):
            continue
        elif min(len(a), len(b)) > 2000 and _within_by_anchors(a, b, m):
            out[i] = True
        elif a and b:
            todo.append((len(a), len(b), i, a, b, m) if len(a) <= len(b) else (len(b), len(a), i, b, a, m))
    todo.sort(key=lambda x: (2 * x[5] > x[0], *x[:3]))  # those with a wide band for their length apart
    for part in _alike_in_length(todo):
        while part:
            blocks, n = (part[-1][0] + 63) // 64, len(part)
            reach = 1 + (max(x[5] for x in part) + 63) // 64
            if 20 * min(blocks, reach) * (0.7 + 0.0008 * n) > n * (1 + 0.02 * blocks):  # microseconds a column, both ways
                for *_, i, a, b, m in part:
                    out[i] = edit_distance(a, b, m) <= m
                break
            kinds = len(set().union(*(set(x[3]) for x in part))) + 2
            room = (kinds * blocks + part[-1][1] + 64) * 8
            now, part = part[: max(1, memory // room)], part[max(1, memory // room) :]
            m = np.array([x[5] for x in now])
            out[[x[2] for x in now]] = _distances([x[3] for x in now], [x[4] for x in now], m) <= m
    return out


def _alike_in_length(todo: list[tuple], most: int = 2048):
    """Runs of pairs whose shorter texts are some as long, to compare in the same blocks of rows."""
    at = 0
    while at < len(todo):
        to, low, limit = at, todo[at][0], max(64, (todo[at][0] * 5 // 4 + 63) // 64 * 64)
        while to < len(todo) and to - at < most and low <= todo[to][0] <= (limit if to - at >= 128 else 2 * limit):
            to += 1
        yield todo[at:to]
        at = to


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)


def _distances(a: list[str], b: list[str], most: np.ndarray) -> np.ndarray:
    """Edit distances of the pairs, no a longer than its b, where they are at most `most`; larger values elsewhere.

    The same letters after both texts, which change no distance, make every a fill the same number of blocks. Only blocks that
    meet the diagonals a path of `most` edits can take are worked on: a block that joins later starts one edit a row
    above the last, one that has left counts as rising by one a column, and neither can lower a distance in the band.
    """
    la, lb = np.array([len(x) for x in a]), np.array([len(x) for x in b])
    blocks = (int(la.max()) + 63) // 64
    order = np.argsort(lb - la, kind="stable")  # pairs end one after the other
    a, b, la, lb, most = [a[i] for i in order], [b[i] for i in order], la[order], lb[order], most[order]
    n, end = len(a), lb + 64 * blocks - la
    width = int(end[-1])
    above, below = int(((most + lb - la) // 2).max()), int(((most - lb + la) // 2).max())
    rows, columns = _points("".join(a)), _points("".join(b))
    there = np.zeros(int(max(rows.max(), columns.max())) + 1, dtype=bool)
    there[rows] = True
    code = np.cumsum(there) - 1  # the letters of a, the padding, and what a lacks
    kinds = int(code[-1]) + 1
    code[~there] = kinds + 1
    pair = np.repeat(np.arange(n), la)
    row = np.arange(len(rows)) - np.repeat(np.cumsum(la) - la, la)
    where = np.zeros((blocks, (kinds + 2) * n), dtype=np.uint64)
    np.bitwise_or.at(where.reshape(-1), (row >> 6) * ((kinds + 2) * n) + code[rows] * n + pair, _ONE << (row & 63).astype(np.uint64))
    start = 64 * np.arange(blocks)[:, None]
    filled = np.clip(la - start, 0, 64).astype(np.uint64)
    where[:, kinds * n : (kinds + 1) * n] = np.where(filled > _TOP, np.uint64(0), _FULL << np.minimum(filled, _TOP))
    text = np.full((width, n), kinds)
    text[np.arange(len(columns)) - np.repeat(np.cumsum(lb) - lb, lb), np.repeat(np.arange(n), lb)] = code[columns]
    text *= n
    text += np.arange(n)
    up = np.full((blocks, n), _FULL)
    down = np.zeros((blocks, n), dtype=np.uint64)
    foot = np.zeros(n, dtype=np.int64)  # distances at the last row worked on
    out = np.zeros(n, dtype=np.int64)
    ends, first = np.unique(end, return_index=True)
    after = dict(zip(ends.tolist(), [*first[1:].tolist(), n]))  # where the pairs left begin once a column is done
    live, begun = 0, -1
    one = np.ones(n, dtype=np.uint64)
    none = np.zeros(n, dtype=np.uint64)
    for j in range(width):
        lo, hi = max(0, (j - above) // 64), min(blocks - 1, (j + below) // 64)
        if hi > begun:
            foot[live:] += 64 * (hi - begun)
            begun = hi
        rise, fall, at = one[live:], none[live:], text[j, live:]
        for w in range(lo, hi + 1):
            eq, p, m = where[w].take(at), up[w, live:], down[w, live:]
            xv = eq | m
            eq |= fall
            xh = eq & p
            xh += p
            xh ^= p
            xh |= eq
            ph = xh | p
            np.invert(ph, out=ph)
            ph |= m
            xh &= p
            rise_out, fall_out = ph >> _TOP, xh >> _TOP
            ph <<= _ONE
            ph |= rise
            xh <<= _ONE
            xh |= fall
            np.bitwise_and(ph, xv, out=m)
            xv |= ph
            np.invert(xv, out=xv)
            np.bitwise_or(xh, xv, out=p)
            rise, fall = rise_out, fall_out
        foot[live:] += rise.view(np.int64)
        foot[live:] -= fall.view(np.int64)
        if (to := after.get(j + 1)) is not None:
            out[live:to] = foot[live:to]
            live = to
    back = np.empty(n, dtype=np.int64)
    back[order] = out
    return back
