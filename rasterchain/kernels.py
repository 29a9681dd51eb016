"""Minimum and maximum filters on two-dimensional arrays (rows first), clipped at the frame.

All maxima are taken through the order-reversing twin of a minimum: the functions take
`lo` (np.minimum or np.maximum) and work for either.
"""

from __future__ import annotations

import heapq
from collections import deque

import numpy as np

from rasterchain import dtypes

MIN, MAX = np.minimum, np.maximum
#: Bytes of a row of a block that takes several filters in the cache.
BLOCK_BYTES = 4096


def neutral(dtype, lo) -> float | int:
    return dtypes.highest(dtype) if lo is MIN else dtypes.lowest(dtype)


def row3(a: np.ndarray, lo=MIN, axis: int = 1, out: np.ndarray | None = None) -> np.ndarray:
    """Three neighbours along an axis by displaced whole-array operands."""
    out = np.copy(a) if out is None else out
    if out is not a:
        out[...] = a
    src = a
    b = np.moveaxis(out, axis, -1)
    s = np.moveaxis(src, axis, -1)
    if s.shape[-1] > 1:
        lo(b[..., 1:], s[..., :-1], out=b[..., 1:])
        lo(b[..., :-1], s[..., 1:], out=b[..., :-1])
    return out


def sep3(a: np.ndarray, lo=MIN, order: str = "xy") -> np.ndarray:
    """The 3x3 filter as a row pass and a column pass, in either order; more axes are filtered after them."""
    for axis in [-1, -2] if order == "xy" else [-2, -1]:
        a = row3(a, lo, axis)
    for axis in range(a.ndim - 2):
        a = row3(a, lo, axis)
    return a


def chain3(a: np.ndarray, n: int, lo=MIN, block_rows: int = 128, together: int = 16, block_cols: int | None = None) -> np.ndarray:
    """n filters of 3x3 in a row. Blocks that stay in the cache take some filters together before the next block.

    A block is read with as many rows and columns on each side as filters run on it, so its own
    pixels are exact. Its width, unless given, follows the bytes of a pixel.
    """
    h, w = a.shape
    if n == 0 or not a.size:
        return a.copy()
    wide = block_cols or max(64, BLOCK_BYTES // a.itemsize)
    cur, nxt = a.copy(), np.empty_like(a)
    size = min(h, block_rows + 2 * together) * min(w, wide + 2 * together)
    u, t = np.empty(size, a.dtype), np.empty(size, a.dtype)
    done = 0
    while done < n:
        k = min(together, n - done)
        for y in range(0, h, block_rows):
            top, bottom = max(0, y - k), min(h, y + block_rows + k)
            for x in range(0, w, wide):
                left, right = max(0, x - k), min(w, x + wide + k)
                m, c = bottom - top, right - left
                p, q = u[: m * c].reshape(m, c), t[: m * c].reshape(m, c)
                p[...] = cur[top:bottom, left:right]
                for _ in range(k):
                    if c > 1:  # pairs, then pairs of pairs; the frame clips
                        lo(p[:, :-1], p[:, 1:], out=q[:, :-1])
                        p[:, 0], p[:, -1] = q[:, 0], q[:, c - 2]
                        lo(q[:, : c - 2], q[:, 1 : c - 1], out=p[:, 1:-1])
                    if m > 1:
                        lo(p[:-1], p[1:], out=q[:-1])
                        p[0], p[-1] = q[0], q[m - 2]
                        lo(q[: m - 2], q[1 : m - 1], out=p[1:-1])
                nxt[y : y + block_rows, x : x + wide] = p[y - top : y - top + block_rows, x - left : x - left + wide]
        cur, nxt = nxt, cur
        done += k
    return cur


def direct(a: np.ndarray, s: int, lo=MIN) -> np.ndarray:
    """Every value of the window compared."""
    fill = neutral(a.dtype, lo)
    p = np.pad(a, s, constant_values=fill)
    out = np.full_like(a, fill)
    for dy in range(2 * s + 1):
        for dx in range(2 * s + 1):
            lo(out, p[dy : dy + a.shape[0], dx : dx + a.shape[1]], out=out)
    return out


def segment(a: np.ndarray, s: int, lo=MIN, axis: int = 1) -> np.ndarray:
    """A segment of 2s + 1 values by doubling runs."""
    b = np.moveaxis(a, axis, -1)
    n = b.shape[-1]
    pad = [(0, 0)] * (b.ndim - 1) + [(s, s)]
    p = np.pad(b, pad, constant_values=neutral(a.dtype, lo))
    width, have = 2 * s + 1, 1
    while have * 2 <= width:
        p = lo(p[..., :-have], p[..., have:])
        have *= 2
    out = p[..., :n] if have == width else lo(p[..., :n], p[..., width - have : width - have + n])
    return np.moveaxis(out, -1, axis)


def segments(a: np.ndarray, s: int, lo=MIN) -> np.ndarray:
    return segment(segment(a, s, lo, 1), s, lo, 0) if s else a.copy()


def running(a: np.ndarray, s: int, lo=MIN, axis: int = 1) -> np.ndarray:
    """Window of 2s + 1 by running extrema from both ends of blocks: three comparisons a value, whatever s."""
    b = np.moveaxis(a, axis, -1)
    n, w = b.shape[-1], 2 * s + 1
    length = -(-(n + 2 * s) // w) * w
    pad = [(0, 0)] * (b.ndim - 1) + [(s, length - n - s)]
    p = np.pad(b, pad, constant_values=neutral(a.dtype, lo)).reshape(*b.shape[:-1], length // w, w)
    ahead = lo.accumulate(p, axis=-1).reshape(*b.shape[:-1], length)
    back = np.flip(lo.accumulate(np.flip(p, -1), axis=-1), -1).reshape(*b.shape[:-1], length)
    out = lo(back[..., :n], ahead[..., w - 1 : w - 1 + n])
    return np.moveaxis(out, -1, axis)


def prefix_suffix(a: np.ndarray, s: int, lo=MIN) -> np.ndarray:
    return running(running(a, s, lo, 1), s, lo, 0) if s else a.copy()


def queue_line(line: list, s: int, lo=MIN) -> list:
    """Window of 2s + 1 by a queue of the values that can still win, each dropped once."""
    n, out, q = len(line), [], deque()
    worse = (lambda x, y: x >= y) if lo is MIN else (lambda x, y: x <= y)
    for i in range(n + s):
        if i < n:
            while q and worse(line[q[-1]], line[i]):
                q.pop()
            q.append(i)
        if i >= s:
            while q[0] < i - 2 * s:
                q.popleft()
            out.append(line[q[0]])
    return out


def queue(a: np.ndarray, s: int, lo=MIN) -> np.ndarray:
    rows = np.array([queue_line(r, s, lo) for r in a.tolist()], a.dtype).reshape(a.shape)
    return np.array([queue_line(c, s, lo) for c in rows.T.tolist()], a.dtype).reshape(a.T.shape).T.copy()


def chords(a: np.ndarray, shape: np.ndarray, lo=MIN) -> np.ndarray:
    """Arbitrary flat element (boolean, odd sides, centred) cut into chords, with a table of runs of powers of two."""
    cy, cx = shape.shape[0] // 2, shape.shape[1] // 2
    runs = []
    for j, row in enumerate(shape):
        edge = np.flatnonzero(np.diff(np.concatenate([[0], row.astype(np.int8), [0]])))
        runs += [(j - cy, x0 - cx, x1 - x0) for x0, x1 in zip(edge[::2], edge[1::2], strict=True)]
    fill = neutral(a.dtype, lo)
    p = np.pad(a, ((cy, cy), (cx, 2 * cx + 1)), constant_values=fill)
    table = {1: p}
    longest = max((n for _, _, n in runs), default=1)
    have = 1
    while have * 2 <= longest:
        q = np.full_like(p, fill)
        q[:, :-have] = lo(table[have][:, :-have], table[have][:, have:])
        table[2 * have] = q
        have *= 2
    out = np.full_like(a, fill)
    for dy, dx, n in runs:
        power = 1 << (int(n).bit_length() - 1)
        rows = slice(cy + dy, cy + dy + a.shape[0])
        for at in {dx, dx + n - power}:
            lo(out, table[power][rows, cx + at : cx + at + a.shape[1]], out=out)
    return out


def row3_inplace(row: np.ndarray, stride: int, lo=MIN) -> np.ndarray:
    """Horizontal filter that overwrites its row stride by stride, saving the value about to be overwritten."""
    n = len(row)
    saved = neutral(row.dtype, lo)
    for at in range(0, n, stride):
        end = min(at + stride, n)
        left = np.concatenate([[saved], row[at : end - 1]]).astype(row.dtype)
        right = np.append(row[at + 1 : end], row[end] if end < n else neutral(row.dtype, lo)).astype(row.dtype)
        saved = row[end - 1]
        row[at:end] = lo(lo(left, row[at:end]), right)
    return row


def rows3_inplace(a: np.ndarray, stride: int, lo=MIN) -> np.ndarray:
    for row in a:
        row3_inplace(row, stride, lo)
    return a


def cols3_inplace(a: np.ndarray, lo=MIN) -> np.ndarray:
    """Vertical filter that overwrites its image with one row kept aside."""
    kept = np.full(a.shape[1], neutral(a.dtype, lo), a.dtype)
    for y in range(len(a)):
        below = a[y + 1] if y + 1 < len(a) else np.full_like(kept, neutral(a.dtype, lo))
        new = lo(lo(kept, a[y]), below)
        kept = a[y].copy()
        a[y] = new
    return a


def filtered(a: np.ndarray, s: int, lo=MIN, method: str = "auto") -> np.ndarray:
    """Erosion (lo = MIN) or dilation (MAX) by the square of side 2s + 1."""
    if s < 0:
        raise ValueError("sizes are not negative")
    if s == 0:
        return a.copy()
    if method == "auto":
        # measured on arrays of these types: chains win up to a few filters only
        method = "chain" if s <= 2 else "prefix_suffix"
    if method == "chain":
        return chain3(a, s, lo)
    return {"direct": direct, "segments": segments, "prefix_suffix": prefix_suffix, "queue": queue}[method](a, s, lo)


def geodesic(a: np.ndarray, mask: np.ndarray, lo=MAX) -> np.ndarray:
    """One geodesic dilation (lo = MAX) or erosion (MIN): the 3x3 filter, clamped by the mask."""
    return (MIN if lo is MAX else MAX)(sep3(a, lo), mask)


def reconstruct(a: np.ndarray, mask: np.ndarray, lo=MAX, cap: int | None = None) -> tuple[np.ndarray, int]:
    """Geodesic filters until one changes nothing, or cap of them; the result and the number that changed something."""
    a = a.astype(np.result_type(a, mask))
    done = 0
    while cap is None or done < cap:
        new = geodesic(a, mask, lo)
        if np.array_equal(new, a):
            break
        a = new
        done += 1
    return a, done


def settled(a: np.ndarray, mask: np.ndarray, lo=MAX, above: np.ndarray | None = None, below: np.ndarray | None = None, rows: int = 1024, pixels: int = 1 << 20) -> np.ndarray:
    """The limit of reconstruct without its length, for a marker that its mask already bounds: by sweeps over blocks of rows.

    Filters are monotone, so any fair order reaches the limit. A sweep takes a value as far as the
    mask lets it pass, in blocks side by side; blocks rest until a neighbour's edge row changes.
    above and below are rows beside the image that stay as they are.
    """
    clamp = MIN if lo is MAX else MAX
    h, w = a.shape
    if not a.size:
        return a.copy()
    n, none = -(-h // rows), neutral(a.dtype, lo)
    v, m = (np.full((n * rows + 2, w), none, a.dtype) for _ in range(2))
    v[1 : h + 1], m[1 : h + 1] = a, mask
    # what stands beside the image is bounded by itself, so sweeps do not change it
    for at, row in ((0, above), (h + 1, below)):
        if row is not None and at < len(v):
            v[at] = m[at] = row
    own = np.arange(rows + 2)

    def sweep(p: np.ndarray, q: np.ndarray, order, inner: slice) -> None:
        """Along the first axis: each plane takes from the one before it and its neighbours there along the last axis."""
        t = np.empty_like(p[0])
        for i, j in order:
            t[...] = p[i]
            lo(t[:, 1:], p[i][:, :-1], out=t[:, 1:])
            lo(t[:, :-1], p[i][:, 1:], out=t[:, :-1])
            to = p[j][:, inner]
            lo(to, t[:, inner], out=to)
            clamp(to, q[j][:, inner], out=to)

    active = np.ones(n, bool)
    share = max(1, pixels // (rows * w))
    while active.any():
        waiting = np.flatnonzero(active)
        for at in range(0, len(waiting), share):
            blocks = waiting[at : at + share]
            active[blocks] = False
            place = blocks[None, :] * rows + own[:, None]  # row by block
            p, q = v[place], m[place]
            first, last = p[1].copy(), p[rows].copy()
            qt = np.ascontiguousarray(q.transpose(2, 1, 0))
            while True:
                before = p[1 : rows + 1].copy()
                sweep(p, q, ((i - 1, i) for i in range(1, rows + 1)), slice(None))
                sweep(p, q, ((i + 1, i) for i in range(rows, 0, -1)), slice(None))
                pt = np.ascontiguousarray(p.transpose(2, 1, 0))
                sweep(pt, qt, ((i - 1, i) for i in range(1, w)), slice(1, rows + 1))
                sweep(pt, qt, ((i + 1, i) for i in range(w - 2, -1, -1)), slice(1, rows + 1))
                p = np.ascontiguousarray(pt.transpose(2, 1, 0))
                moved = (p[1 : rows + 1] != before).any(axis=(0, 2))
                # blocks still on the move go on together; a few of many are taken up again with their neighbours
                if moved.sum() * 2 <= len(blocks):
                    break
            v[place[1 : rows + 1]] = p[1 : rows + 1]
            active[blocks[moved]] = True
            up, down = blocks[(p[1] != first).any(axis=1)], blocks[(p[rows] != last).any(axis=1)]
            active[up[up > 0] - 1] = True
            active[down[down < n - 1] + 1] = True
    return v[1 : h + 1]


def rebuilt(a: np.ndarray, mask: np.ndarray, lo=MAX) -> np.ndarray:
    """reconstruct without its length."""
    return settled(geodesic(a.astype(np.result_type(a, mask)), mask, lo), mask, lo)  # the first filter orders marker and mask


def reconstruct_heap(a: np.ndarray, mask: np.ndarray, lo=MAX) -> np.ndarray:
    """Reconstruction by a hierarchical queue: pixels leave in order of value and flood their neighbours."""
    a = geodesic(a.astype(np.result_type(a, mask)), mask, lo)  # the first filter orders marker and mask
    sign = -1 if lo is MAX else 1
    v, m = ([[sign * x for x in row] for row in b.tolist()] for b in (a, mask.astype(a.dtype)))
    h, w = a.shape
    heap = [(v[y][x], y, x) for y in range(h) for x in range(w)]
    heapq.heapify(heap)
    while heap:
        value, y, x = heapq.heappop(heap)
        if value != v[y][x]:
            continue
        for j in range(max(0, y - 1), min(h, y + 2)):
            for i in range(max(0, x - 1), min(w, x + 2)):
                new = max(value, m[j][i])
                if new < v[j][i]:
                    v[j][i] = new
                    heapq.heappush(heap, (new, j, i))
    return np.array([[sign * x for x in row] for row in v], a.dtype).reshape(h, w)


def frame(shape: tuple[int, int]) -> np.ndarray:
    """True on the border of the image."""
    out = np.ones(shape, bool)
    out[1:-1, 1:-1] = False
    return out


def hmax(a: np.ndarray, h, arith: str = "real") -> tuple[np.ndarray, int]:
    return reconstruct(dtypes.lowered(a, h, arith), a)


def hfill(a: np.ndarray, marker: np.ndarray | None = None) -> tuple[np.ndarray, int]:
    return reconstruct(hfill_marker(a) if marker is None else marker, a, MIN)


def hfill_marker(a: np.ndarray) -> np.ndarray:
    return np.where(frame(a.shape), a, a.max())


def raobj_marker(a: np.ndarray) -> np.ndarray:
    return np.where(frame(a.shape), a, a.min())


def raobj(a: np.ndarray, marker: np.ndarray | None = None) -> tuple[np.ndarray, int]:
    r, k = reconstruct(raobj_marker(a) if marker is None else marker, a)
    return a - r, k


def open_rec(a: np.ndarray, s: int) -> tuple[np.ndarray, int]:
    """The opening by reconstruction, and the chain length of its reconstruction."""
    return reconstruct(filtered(a, s, MIN), a)


def residuals(a: np.ndarray, conditional: bool = True, early: bool = True) -> tuple[np.ndarray, np.ndarray, int]:
    """Step (counted from 1; 0: none) and value of the largest loss of a chain of erosions; the first of equal losses counts."""
    d, r = np.zeros(a.shape, np.int32), np.zeros(a.shape, a.dtype)
    steps = 0
    for j in range(1, max(a.shape) + 1):
        new = sep3(a, MIN)
        loss = a - new
        if not loss.any() and early:
            break
        more = loss > r
        if conditional:
            r[more] = loss[more]
            d[more] = j
        else:
            d = np.where(more, j, d)
            r = np.maximum(r, loss)
        steps += bool(loss.any())
        a = new
    return d, r, steps


def lipschitz_step(d: np.ndarray) -> np.ndarray:
    return np.minimum(d, sep3(d, MIN) + 1)


def lipschitz(d: np.ndarray) -> tuple[np.ndarray, int]:
    done = 0
    while True:
        new = lipschitz_step(d)
        if np.array_equal(new, d):
            return d, done
        d, done = new, done + 1


def lipschitz_closed(d: np.ndarray) -> np.ndarray:
    """The fixed point at once: least eroded value plus size over all sizes up to the largest distance."""
    out, e = d.copy(), d
    for j in range(1, int(d.max()) + 1 if d.size else 0):
        e = sep3(e, MIN)
        np.minimum(out, e + j, out=out)
    return out


def opened(a: np.ndarray, s: int) -> np.ndarray:
    return filtered(filtered(a, s, MIN), s, MAX)


def closed(a: np.ndarray, s: int) -> np.ndarray:
    return filtered(filtered(a, s, MAX), s, MIN)


def granulometry(a: np.ndarray, s_max: int, family: str = "open") -> list:
    """Sums of the openings (closings) of sizes 0 to s_max; the first filters of all sizes are shared."""
    lo, hi = (MIN, MAX) if family == "open" else (MAX, MIN)
    wide = np.float64 if a.dtype.kind == "f" else np.int64
    sums, e = [a.sum(dtype=wide).item()], a
    for s in range(1, s_max + 1):
        e = sep3(e, lo)
        # short chains beat running extrema on small images
        sums.append(filtered(e, s, hi, "chain" if s <= 4 else "prefix_suffix").sum(dtype=wide).item())
    return sums


def asf(a: np.ndarray, s: int, first: str = "open", fused: bool = False) -> np.ndarray:
    """Openings and closings of sizes 1 to s in turn; fused: neighbouring dilations (erosions) as one."""
    a_lo, b_lo = (MIN, MAX) if first == "open" else (MAX, MIN)
    if not fused:
        for k in range(1, s + 1):
            a = filtered(filtered(a, k, a_lo, "chain"), k, b_lo, "chain")
            a = filtered(filtered(a, k, b_lo, "chain"), k, a_lo, "chain")
        return a
    steps: list[list] = []
    for k in range(1, s + 1):
        for lo in (a_lo, b_lo, b_lo, a_lo):
            if steps and steps[-1][0] is lo:
                steps[-1][1] += k
            else:
                steps.append([lo, k])
    for lo, k in steps:
        a = filtered(a, k, lo, "prefix_suffix")
    return a


def labelled(a: np.ndarray) -> np.ndarray:
    """8-connected components of the pixels above 0, named by their largest linear index plus 1; 0 elsewhere."""
    ids = (np.arange(a.size, dtype=np.int64).reshape(a.shape) + 1) * (a > 0)
    return reconstruct(ids, np.where(a > 0, a.size + 1, 0))[0]
