"""Suffix arrays by induced sorting, and permuted common prefixes, on numpy arrays.

Suffix types and leftmost-smaller (LMS) positions are found with array operations.  Inducing goes bucket by bucket: while a
bucket is scanned its predecessors are dealt to their buckets in one stable sort, so each suffix is touched a constant number
of times.  Reduced strings with large alphabets, a third of the length or less, are induced by a plain scan instead.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64
SMALL_ALPHABET = 512


def _types(s: np.ndarray) -> np.ndarray:
    """True where the suffix is smaller than its right neighbour (the empty suffix is the smallest)."""
    n = len(s)
    up = np.zeros(n, np.int8)
    up[:-1] = np.sign(s[1:].astype(np.int64) - s[:-1].astype(np.int64))
    up[-1] = -1
    nxt = np.where(up != 0, np.arange(n), n)
    nxt = np.minimum.accumulate(nxt[::-1])[::-1]
    return up[nxt] > 0


def _induce_buckets(s: np.ndarray, small: np.ndarray, lms: np.ndarray, k: int) -> np.ndarray:
    """Suffix array induced from LMS suffixes given in order, by bucket."""
    n = len(s)
    lms_of = _deal(s, lms)
    left = [[] for _ in range(k)]
    left[s[n - 1]].append(np.array([n - 1], np.int64))
    done_l: list[np.ndarray] = [np.zeros(0, np.int64)] * k

    def send(into, p):
        for c, part in _deal(s, p).items():
            into[c].append(part)

    for c in range(k):
        out, wave = [], np.concatenate(left[c]) if left[c] else np.zeros(0, np.int64)
        while len(wave):
            out.append(wave)
            p = wave[wave > 0] - 1
            p = p[~small[p]]
            same = s[p] == c
            send(left, p[~same])
            wave = p[same]
        done_l[c] = np.concatenate(out) if out else wave
        if c in lms_of:
            send(left, lms_of[c] - 1)
    right = [[] for _ in range(k)]
    done = [None] * k
    for c in range(k - 1, -1, -1):
        out, wave = [], np.concatenate(right[c]) if right[c] else np.zeros(0, np.int64)
        while len(wave):
            out.append(wave)
            p = wave[wave > 0] - 1
            p = p[small[p]]
            same = s[p] == c
            send(right, p[~same])
            wave = p[same]
        p = done_l[c][::-1]
        p = p[p > 0] - 1
        send(right, p[small[p]])
        done[c] = np.concatenate([done_l[c], (np.concatenate(out) if out else np.zeros(0, np.int64))[::-1]])
    return np.concatenate(done)


def _deal(s: np.ndarray, p: np.ndarray) -> dict[int, np.ndarray]:
    """Positions by their symbol, order kept."""
    if not len(p):
        return {}
    c = s[p]
    order = np.argsort(c, kind="stable")
    c = c[order]
    cut = np.flatnonzero(np.r_[True, c[1:] != c[:-1]])
    return {int(c[a]): p[order[a:b]] for a, b in zip(cut, np.r_[cut[1:], len(c)])}


def _induce_scan(s: np.ndarray, small: np.ndarray, lms: np.ndarray, k: int) -> np.ndarray:
    """The same for large alphabets, one suffix after the other."""
    n = len(s)
    sizes = np.bincount(s, minlength=k)
    ends = np.cumsum(sizes)
    t, sl = s.tolist(), small.tolist()
    sa = [-1] * n
    tail = ends.tolist()
    for i in lms[::-1].tolist():
        tail[t[i]] -= 1
        sa[tail[t[i]]] = i
    head = (ends - sizes).tolist()
    c = t[n - 1]
    sa[head[c]] = n - 1
    head[c] += 1
    for i in range(n):
        j = sa[i] - 1
        if j >= 0 and not sl[j]:
            c = t[j]
            sa[head[c]] = j
            head[c] += 1
    tail = ends.tolist()
    for i in range(n - 1, -1, -1):
        j = sa[i] - 1
        if j >= 0 and sl[j]:
            c = t[j]
            tail[c] -= 1
            sa[tail[c]] = j
    return np.array(sa, np.int64)


def suffix_array(s: np.ndarray) -> np.ndarray:
    """Start positions of the suffixes of an array of small non-negative integers, in order."""
    n = len(s)
    if n < 2:
        return np.arange(n, dtype=np.int64)
    k = int(s.max()) + 1
    small = _types(s)
    induce = _induce_buckets if k <= SMALL_ALPHABET else _induce_scan
    is_lms = small.copy()
    is_lms[1:] &= ~small[:-1]
    is_lms[0] = False
    lms = np.flatnonzero(is_lms)
    if len(lms) > 1:
        # leftmost-smaller substrings come out sorted when induced from any order of their starts
        sa = induce(s, small, lms, k)
        ordered = sa[is_lms[sa]]
        base = 0x9E3779B97F4A7C15
        v = (s.astype(_U) + _U(1)) * _U(0xD6E8FEB86659FD93)
        v ^= v >> _U(32)
        sums = np.cumsum(np.r_[_U(0), v * np.cumprod(np.r_[_U(1), np.full(n - 1, base, _U)])])
        end = np.r_[lms[1:] + 1, n]
        inverse = np.cumprod(np.r_[_U(1), np.full(n - 1, pow(base, -1, 1 << 64), _U)])
        digest = (sums[end] - sums[lms]) * inverse[lms] + (end - lms).astype(_U) * _U(0xA3B195354A39B70D)
        rank = np.empty(n, np.int64)
        rank[lms] = np.arange(len(lms))
        d = digest[rank[ordered]]
        d_len = (end - lms)[rank[ordered]]
        differs = np.r_[False, (d[1:] != d[:-1]) | (d_len[1:] != d_len[:-1]) | (ordered[1:] == lms[-1]) | (ordered[:-1] == lms[-1])]
        names = np.cumsum(differs)
        reduced = np.empty(len(lms), np.int64)
        reduced[rank[ordered]] = names
        if names[-1] + 1 < len(lms):
            lms = lms[suffix_array(reduced)]
        else:
            lms = ordered
    return induce(s, small, lms, k)


def common_prefixes(b: np.ndarray, sa: np.ndarray) -> np.ndarray:
    """Per place of the suffix array, the common prefix with the place before (bytes); made in text order.

    A position whose left neighbour repeats its predecessor's left neighbour inherits one less than the position before it;
    only the others are compared, eight bytes a step.
    """
    n = len(b)
    phi = np.full(n, -1, np.int64)
    phi[sa[1:]] = sa[:-1]
    pad = np.r_[b, np.zeros(8, np.uint8)].astype(_U)
    words = np.zeros(n + 1, _U)
    for j in range(8):
        words[: n + 1] |= pad[j : j + n + 1][: n + 1] << _U(8 * j) if j + n + 1 <= n + 8 else np.r_[pad[j:], np.zeros(n + 1 - (n + 8 - j), _U)] << _U(8 * j)
    prev = np.arange(n) - 1
    inherits = (phi > 0) & (prev >= 0)
    i = np.flatnonzero(inherits)
    inherits[i] = b[i - 1] == b[phi[i] - 1]
    plcp = np.zeros(n, np.int64)
    live = np.flatnonzero(~inherits & (phi >= 0))
    x, y = live.copy(), phi[live]
    while len(live):
        inside = (x < n) & (y < n)
        w = np.where(inside, words[np.minimum(x, n)] ^ words[np.minimum(y, n)], _U(1))
        same = w == 0
        tail = np.bitwise_count((w & (~w + _U(1))) - _U(1)).astype(np.int64) // 8
        room = n - np.maximum(x, y)
        stop = ~same | (room <= 8)
        step = np.minimum(np.where(same, 8, tail), np.maximum(room, 0))
        plcp[live] += step
        live, x, y = live[~stop], x[~stop] + 8, y[~stop] + 8
    first = np.where(inherits, -1, np.arange(n))
    first = np.maximum.accumulate(first)
    plcp = np.where(inherits, plcp[first] - (np.arange(n) - first), plcp)
    return np.maximum(plcp, 0)[sa]
