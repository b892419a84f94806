"""Entropy coding of integer indices: an adaptive binary range coder in lockstep over lanes, and diagnostics.

An index becomes a zero flag, a sign, a truncated unary magnitude and an Exp-Golomb tail. Zero flag and magnitude
bins are adaptive in a context taken from the two magnitudes before, so a decoder can follow. All lanes of a task
advance bin by bin as numpy vectors; the bytes equal those of coding each lane alone.
"""

from __future__ import annotations

import lzma

import numpy as np

# 11-bit probabilities, adaptation shift 5, renormalisation below 2^24, five flush bytes.
PROB_BITS, SHIFT, TOP, FLUSH = 11, 5, 1 << 24, 5
HALF = 1 << (PROB_BITS - 1)
N_CTX, UNARY = 6, 14
#: Adaptive slots of one stream: zero flags, then unary bins, each by context.
SLOTS = N_CTX * (1 + UNARY)
BYPASS = -1


def contexts(k: np.ndarray) -> np.ndarray:
    """Context of each index from 2|k[-1]| + |k[-2]|: 0, 1-2, 3-5, 6-11, 12-23, 24 and more."""
    m = np.minimum(np.abs(k), 1 << 40)
    one, two = np.zeros_like(m), np.zeros_like(m)
    one[..., 1:], two[..., 2:] = m[..., :-1], m[..., :-2]
    return np.searchsorted([1, 3, 6, 12, 24], 2 * one + two, side="right")


def binarize(k: np.ndarray, extra: np.ndarray | None = None, n_extra: int = 1, ctx: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(slot, bit) of every bin of one lane, in coding order; slot BYPASS is an even bit."""
    k = np.asarray(k, np.int64)
    ctx = contexts(k) if ctx is None else ctx
    ctx = ctx if extra is None else ctx * n_extra + extra
    m = np.abs(k).astype(np.uint64)
    n = len(k)
    unary = np.minimum(m, UNARY + 1).astype(np.int64) - 1  # ones in the prefix (for nonzero)
    has_tail = m > UNARY
    tail = np.where(has_tail, m - np.uint64(UNARY + 1) + np.uint64(1), np.uint64(1))
    width = np.zeros(n, np.int64)
    if has_tail.any():
        t = tail[has_tail]
        w = np.zeros(len(t), np.int64)
        for s in (32, 16, 8, 4, 2, 1):
            big = t >= (np.uint64(1) << np.uint64(s))
            w[big] += s
            t = np.where(big, t >> np.uint64(s), t)
        width[has_tail] = w
    nz = k != 0
    count = np.ones(n, np.int64)
    # prefix: ``unary`` ones then a zero, or UNARY ones and no zero
    count[nz] = 2 + np.where(unary[nz] >= UNARY, UNARY, unary[nz] + 1) + np.where(has_tail[nz], 2 * width[nz] + 1, 0)
    start = np.cumsum(count) - count
    total = int(count.sum())
    slot, bit = np.full(total, BYPASS, np.int16), np.zeros(total, np.uint8)
    slot[start], bit[start] = ctx, nz
    s = start[nz]
    bit[s + 1] = k[nz] < 0
    groups = N_CTX * n_extra
    for u in range(UNARY):
        on = nz & (unary >= u)
        at = start[on] + 2 + u
        slot[at], bit[at] = groups + ctx[on] * UNARY + u, unary[on] > u
    for j in range(int(width.max(initial=0)) + 1):  # width zeros, a one, then width low bits
        on = has_tail & (width == j)
        if on.any():
            at = start[on] + 2 + UNARY
            bit[at + j] = 1
            for b in range(j):
                bit[at + j + 1 + b] = (tail[on] >> np.uint64(j - 1 - b)) & np.uint64(1)
    return slot, bit


#: So few lanes are coded one after another: steps of numpy cost more than they save, and bins need not be held at once.
FEW_LANES, LANE_BLOCK = 32, 1 << 14


def _encode_lane(k: np.ndarray, extra: np.ndarray | None, n_extra: int) -> bytes:
    """The bytes of one lane, from LANE_BLOCK indices at a time."""
    prob, low, rng, out = [HALF] * (SLOTS * n_extra + 1), 0, (1 << 32) - 1, bytearray()

    def put(v: int) -> None:
        if v > 255:  # a carry
            at = len(out) - 1
            while out[at] == 255:
                out[at] = 0
                at -= 1
            out[at] += 1
        out.append(v & 255)

    for at in range(0, len(k), LANE_BLOCK):
        back, end = max(at - 2, 0), at + LANE_BLOCK
        slots, bits = binarize(k[at:end], None if extra is None else extra[at:end], n_extra, contexts(k[back:end])[at - back :])
        for s, b in zip(slots.tolist(), bits.tolist(), strict=True):
            p = prob[s]  # BYPASS reads the last, which stays at one half
            bound = (rng >> PROB_BITS) * p
            if b:
                low += bound
                rng -= bound
                if s >= 0:
                    prob[s] = p - (p >> SHIFT)
            else:
                rng = bound
                if s >= 0:
                    prob[s] = p + (((1 << PROB_BITS) - p) >> SHIFT)
            if rng < TOP:
                put(low >> 24)
                low = (low & (TOP - 1)) << 8
                rng <<= 8
    for _ in range(FLUSH):
        put(low >> 24)
        low = (low & (TOP - 1)) << 8
    return bytes(out)


def encode_lanes(lanes: list[np.ndarray], extra: list[np.ndarray] | None = None, n_extra: int = 1) -> list[bytes]:
    """Range-coded bytes of each lane of indices."""
    if len(lanes) <= FEW_LANES:
        return [_encode_lane(np.asarray(k, np.int64), None if extra is None else extra[i], n_extra) for i, k in enumerate(lanes)]
    bins = [binarize(k, None if extra is None else extra[i], n_extra) for i, k in enumerate(lanes)]
    order = sorted(range(len(bins)), key=lambda i: -len(bins[i][0]))
    sizes = np.array([len(bins[i][0]) for i in order], np.int64)
    if not len(sizes):
        return []
    steps, n = int(sizes[0]), len(order)
    slots, bits = np.full((steps, n), BYPASS, np.int16), np.zeros((steps, n), np.uint8)
    for j, i in enumerate(order):
        slots[: sizes[j], j], bits[: sizes[j], j] = bins[i]
    active = n - np.searchsorted(sizes[::-1], np.arange(1, steps + 1), "left")  # lanes still coding at each step
    prob = np.full((n, SLOTS * n_extra + 1), HALF, np.int64)  # the last slot stays at one half
    low, rng = np.zeros(n, np.int64), np.full(n, (1 << 32) - 1, np.int64)
    out, used = np.zeros((n, int(steps * 1.6 / 8) * 2 + 64), np.int64), np.zeros(n, np.int64)
    rows = np.arange(n)
    for t in range(steps):
        a = int(active[t])
        r, sl, b = rows[:a], slots[t, :a], bits[t, :a].astype(bool)
        p = prob[r, sl]
        bound = (rng[:a] >> PROB_BITS) * p
        np.add(low[:a], bound, out=low[:a], where=b)
        rng[:a] = np.where(b, rng[:a] - bound, bound)
        adapted = np.where(b, p - (p >> SHIFT), p + (((1 << PROB_BITS) - p) >> SHIFT))
        prob[r, sl] = np.where(sl == BYPASS, HALF, adapted)
        small = np.flatnonzero(rng[:a] < TOP)
        if len(small):
            if int(used.max()) + FLUSH + 2 >= out.shape[1]:
                out = np.pad(out, ((0, 0), (0, out.shape[1])))
            out[small, used[small]] = low[small] >> 24
            used[small] += 1
            low[small] = (low[small] & (TOP - 1)) << 8
            rng[small] <<= 8
    if int(used.max()) + FLUSH + 2 >= out.shape[1]:
        out = np.pad(out, ((0, 0), (0, FLUSH + 2)))
    for _ in range(FLUSH):
        out[rows, used] = low >> 24
        used += 1
        low = (low & (TOP - 1)) << 8
    result: list[bytes] = [b""] * n
    for j, i in enumerate(order):
        row = out[j, : used[j]]
        for at in np.flatnonzero(row > 255)[::-1].tolist():  # carries, from the end
            while at >= 0 and row[at] > 255:
                row[at] &= 255
                at -= 1
                row[at] += 1
        result[i] = row.astype(np.uint8).tobytes()
    return result


class RangeDecoder:
    """Decodes one lane, bin by bin."""

    def __init__(self, data: bytes, n_slots: int = SLOTS):
        self.data, self.at = data + bytes(8), 4
        self.code, self.range = int.from_bytes(self.data[:4], "big"), (1 << 32) - 1
        self.prob = [HALF] * n_slots

    def bit(self, slot: int) -> int:
        p = HALF if slot < 0 else self.prob[slot]
        bound = (self.range >> PROB_BITS) * p
        if self.code < bound:
            self.range, b, p = bound, 0, p + (((1 << PROB_BITS) - p) >> SHIFT)
        else:
            self.code -= bound
            self.range, b, p = self.range - bound, 1, p - (p >> SHIFT)
        if slot >= 0:
            self.prob[slot] = p
        if self.range < TOP:
            self.range <<= 8
            self.code = self.code << 8 | self.data[self.at]
            self.at += 1
        return b

    def index(self, before: int, before2: int) -> int:
        level = 2 * before + before2
        ctx = sum(level >= e for e in (1, 3, 6, 12, 24))
        if not self.bit(ctx):
            return 0
        negative, m = self.bit(BYPASS), 1
        while m <= UNARY and self.bit(N_CTX + ctx * UNARY + m - 1):
            m += 1
        if m > UNARY:
            width = 0
            while not self.bit(BYPASS):
                width += 1
            v = 1
            for _ in range(width):
                v = v << 1 | self.bit(BYPASS)
            m = UNARY + v
        return -m if negative else m


def decode_lane(data: bytes, n: int) -> np.ndarray:
    d, out, a, b = RangeDecoder(data), np.zeros(n, np.int64), 0, 0
    for t in range(n):
        out[t] = k = d.index(a, b)
        a, b = abs(k), a
    return out


def coded_sizes(lanes: list[np.ndarray]) -> np.ndarray:
    return np.array([len(b) for b in encode_lanes(lanes)], np.int64)


# --- generic back ends and diagnostics -------------------------------------------------------------------------


def pack_ints(k: np.ndarray) -> bytes:
    """The narrowest fixed width that holds all indices."""
    k = np.asarray(k, np.int64)
    top = int(np.abs(k).max(initial=0))
    return k.astype("<i1" if top < 128 else "<i2" if top < 1 << 15 else "<i4" if top < 1 << 31 else "<i8").tobytes()


def generic_size(k: np.ndarray, kind: str) -> int:
    raw = pack_ints(k)
    if kind == "xz":
        return len(lzma.compress(raw, preset=6))
    import zstandard

    return len(zstandard.ZstdCompressor(level=12).compress(raw))


def xz_raw_size(x: np.ndarray) -> int:
    return len(lzma.compress(np.asarray(x, "<i8").tobytes(), preset=6))


def empirical_bits(k: np.ndarray, by: np.ndarray | None = None) -> float:
    """Order-0 (or conditional) empirical entropy in bits for each value: a bound-type diagnostic, not a rate."""
    k = np.asarray(k)
    if not len(k):
        return 0.0
    total = 0.0
    for g in np.unique(by) if by is not None else [None]:
        part = k if g is None else k[by == g]
        c = np.unique(part, return_counts=True)[1]
        total -= float((c * np.log2(c / len(part))).sum())
    return total / len(k)


def adaptive_ideal_bits(k: np.ndarray) -> float:
    """Bits that the adaptive bit model itself assigns, without the range coder's rounding and flush."""
    slot, bit = binarize(k)
    prob, bits = np.full(SLOTS + 1, HALF, np.int64), 0.0
    for s, b in zip(slot.tolist(), bit.tolist(), strict=True):
        p = int(prob[s]) if s >= 0 else HALF
        bits -= np.log2((2048 - p if b else p) / 2048)
        if s >= 0:
            prob[s] = p - (p >> SHIFT) if b else p + ((2048 - p) >> SHIFT)
    return float(bits)


#: Residuals whose densities are held at a time.
MIXTURE_BLOCK = 1 << 14


def mixture_bits(resid: np.ndarray, family: str = "mixture") -> float:
    """Code length of integer residuals under a causal mixture of discretised densities over geometric scales.

    ``laplace``: Laplace densities only. ``flat``: uniform densities of geometric widths only. ``mixture``: both, and
    a box on the support seen so far, which a uniform source needs to be read at its true entropy.
    """
    s = np.asarray(resid)
    n = len(s)
    if not n:
        return 0.0
    scales = 2.0 ** np.arange(-1, int(np.log2(float(np.abs(s).max()) + 2)) + 3)
    decay = np.exp(-1 / scales)
    norm, widths = np.log2((1 - decay) / (1 + decay)), np.ceil(scales)
    many = len(scales) * (2 if family == "mixture" else 1) + (family == "mixture")
    # causal Bayesian weights with a little sharing, so that a late winner can take over
    share, w, one, bits, hi, lo = 1e-4, np.full(many, 1 / many), np.ones(many), 0.0, 0.0, 0.0
    for at in range(0, n, MIXTURE_BLOCK):
        v = s[at : at + MIXTURE_BLOCK].astype(np.float64)
        r, experts = np.abs(v)[:, None], []
        if family in ("laplace", "mixture"):
            experts.append(norm - r / scales * np.log2(np.e))
        if family in ("flat", "mixture"):
            experts.append(np.where(r <= widths, -np.log2(2 * widths + 1), -60.0))
        if family == "mixture":
            high, low = np.maximum.accumulate(np.r_[hi, v]), np.minimum.accumulate(np.r_[lo, v])
            hi, lo, high, low = high[-1], low[-1], high[:-1], low[:-1]
            seen = np.arange(at, at + len(v)) + 2.0
            experts.append(np.where((v >= low) & (v <= high), -np.log2(high - low + 1) + np.log2(1 - 2 / (seen + 2)), -60.0)[:, None])
        logp = np.concatenate(experts, axis=1)  # ticks x experts
        top = logp.max(axis=1)
        totals = []
        for p in np.exp2(logp - top[:, None]):
            w *= p
            tot = w.dot(one)
            totals.append(tot)
            w *= (1 - share) / tot
            w += share / many
        bits -= float(top.sum() + np.log2(totals).sum())
    return bits
