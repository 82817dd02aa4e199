"""Suffix arrays by induced sorting in numpy, and permuted common prefixes.

Suffixes are classified as smaller or larger than their right neighbour; the leftmost smaller ones (LMS) are
sorted by their substrings through one induction, named, and sorted as a reduced string by recursion; a second
induction places all suffixes. Over a small alphabet induction goes bucket by bucket, each bucket as one vectorised
batch. The reduced string has a large alphabet, where a bucket holds a handful of suffixes; there several buckets form a batch,
as many as have no suffix that is induced by another of the batch. Both ways are steps of the same recursion.
"""

from __future__ import annotations

import numpy as np

#: Alphabets up to this size are induced bucket by bucket, larger ones in batches of buckets.
SMALL_ALPHABET = 1024


def classify(text: np.ndarray) -> np.ndarray:
    """True where a suffix is smaller than the next one; the empty suffix at the end is the smallest."""
    n = len(text)
    rise = np.zeros(n, np.int8)
    if n > 1:
        rise[:-1] = np.sign(text[1:].astype(np.int64) - text[:-1])
    rise[n - 1 :] = -1
    following = np.minimum.accumulate(np.where(rise != 0, np.arange(n), n)[::-1])[::-1]  # the next that is decided
    return rise[following] > 0


def leftmost_smaller(smaller: np.ndarray) -> np.ndarray:
    return np.flatnonzero(smaller[1:] & ~smaller[:-1]) + 1


def _induce_small(text: np.ndarray, smaller: np.ndarray, seeds: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The suffix array induced from `seeds`, the LMS suffixes in order. ends: where each symbol's bucket ends."""
    n, symbols = len(text), len(ends)
    starts = np.concatenate([[0], ends[:-1]])
    out = np.full(n, -1, np.int64)
    seed_ends = np.cumsum(np.bincount(text[seeds], minlength=symbols))
    seed_starts = np.concatenate([[0], seed_ends[:-1]])
    head = starts.copy()
    out[head[text[n - 1]]] = n - 1
    head[text[n - 1]] += 1

    def before(found: np.ndarray, kind: bool) -> np.ndarray:
        """Left neighbours of `found`, in order, that are of the kind."""
        left = found[found > 0] - 1
        return left[smaller[left] == kind]

    def deal(left: np.ndarray, at: np.ndarray, sign: int) -> None:
        symbol = text[left]
        order = np.argsort(symbol, kind="stable")
        count = np.bincount(symbol, minlength=symbols)
        first = np.cumsum(count) - count
        ranked = symbol[order]
        out[at[ranked] + sign * (np.arange(len(left)) - first[ranked])] = left[order]
        at += sign * count

    for c in range(symbols):
        done = starts[c]
        if ends[c] == done:
            continue
        while done < head[c]:  # chains of one symbol grow the bucket while it is read
            upto = head[c]
            left = before(out[done:upto], False)
            done = upto
            same = left[text[left] == c]
            out[head[c] : head[c] + len(same)] = same
            head[c] += len(same)
        left = np.concatenate([before(out[starts[c] : head[c]], False), before(seeds[seed_starts[c] : seed_ends[c]], False)])
        left = left[text[left] != c]
        if len(left):
            deal(left, head, 1)
    tail = ends - 1
    for c in range(symbols - 1, -1, -1):
        done = ends[c]
        if starts[c] == done:
            continue
        while done - 1 > tail[c]:
            downto = tail[c] + 1
            left = before(out[downto:done][::-1], True)
            done = downto
            same = left[text[left] == c]
            out[tail[c] - np.arange(len(same))] = same
            tail[c] -= len(same)
        left = before(out[starts[c] : ends[c]][::-1], True)
        left = left[text[left] != c]
        if len(left):
            deal(left, tail, -1)
    return out


def _batches(near: np.ndarray, symbols: np.ndarray):
    """(first, last) of runs of buckets none of which needs another of its run. near: for each bucket in order the symbol,
    nearest to its own, of a suffix that induces one of its suffixes; symbols: those of the buckets. Both grow."""
    k, n = 0, len(symbols)
    while k < n:
        width, stop = 64, n
        while True:
            found = np.flatnonzero(near[k + 1 : k + 1 + width] >= symbols[k])
            if len(found):
                stop = k + 1 + int(found[0])
                break
            if k + 1 + width >= n:
                break
            width *= 2
        yield k, stop
        k = stop


def _place(rank: np.ndarray, own: np.ndarray, symbol: np.ndarray, run: np.ndarray, parent: np.ndarray, follows: np.ndarray, slot: np.ndarray) -> None:
    """Rank the suffixes `own`, sorted by symbol in the order of induction: within a bucket by the length of their run of the
    symbol and then by the suffix behind the run, which is ranked already. follows: the symbol of that suffix where it is of
    the same kind, else one that no bucket needs."""
    heads = np.flatnonzero(np.concatenate([[True], symbol[1:] != symbol[:-1]])) if len(own) else np.zeros(0, np.int64)
    if not len(heads):
        return
    near = np.maximum.reduceat(follows, heads)
    ends = np.append(heads[1:], len(own))
    for a, b in _batches(near, symbol[heads]):
        lo, hi = heads[a], ends[b - 1]
        part = own[lo:hi]
        if hi - lo > 1:
            part = part[np.lexsort((rank[parent[lo:hi]], run[lo:hi], symbol[lo:hi]))]
        rank[part] = slot[lo:hi]


def _induce_large(text: np.ndarray, smaller: np.ndarray, seeds: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The same for large alphabets. A run of one symbol is taken at once: a larger suffix with a longer run comes later, a
    smaller one earlier, and both are induced by the suffix behind the run, whose symbol is another."""
    n, symbols, text = len(text), len(ends), text.astype(np.int64)
    starts = np.concatenate([[0], ends[:-1]])
    changes = text[1:] != text[:-1]
    behind = np.append(np.flatnonzero(changes) + 1, n)[np.concatenate([[0], np.cumsum(changes)])]
    run = behind - np.arange(n)
    rank = np.full(n + 1, -1, np.int64)
    after = np.append(text, -1)
    kind = np.append(smaller, True)

    def slots(symbol: np.ndarray, at_end: bool) -> np.ndarray:
        """Where the suffixes of one kind, sorted by symbol, stand: at the beginning or the end of their buckets."""
        count = np.bincount(symbol, minlength=symbols)
        inside = np.arange(len(symbol)) - (np.cumsum(count) - count)[symbol]
        return inside + (ends - count if at_end else starts)[symbol]

    rank[seeds] = slots(text[seeds], True)
    large = np.flatnonzero(~smaller)
    large = large[np.argsort(text[large], kind="stable")]
    parent = behind[large]
    _place(rank, large, text[large], run[large], parent, np.where(kind[parent], -1, after[parent]), slots(text[large], False))
    small = np.flatnonzero(smaller)
    small = small[np.argsort(text[small], kind="stable")]
    slot = slots(text[small], True)
    turned = small[::-1]  # the largest symbols first, and inside a bucket the last suffix first
    parent = behind[turned]
    np.subtract(n, rank, out=rank)  # ranks count down, so that what comes last is placed first
    _place(rank, turned, -text[turned], run[turned], parent, np.where(kind[parent], -after[parent], -symbols), n - slot[::-1])
    np.subtract(n, rank, out=rank)
    out = np.empty(n, np.int64)
    out[rank[:n]] = np.arange(n)
    return out


def _names(text: np.ndarray, order: np.ndarray, lms: np.ndarray) -> np.ndarray:
    """A rank for each LMS substring of `order`, equal substrings alike."""
    n = len(text)
    stop = np.full(n + 1, n, np.int64)  # where the substring that starts here ends, itself included
    stop[lms[:-1]] = lms[1:]
    size = np.minimum(stop[order] + 1, n) - order
    a, b = order[:-1], order[1:]
    tied = np.flatnonzero((size[:-1] == size[1:]) & (stop[a] < n) & (stop[b] < n))
    differs = np.ones(len(a), bool)
    differs[tied] = False
    k = 0
    while len(tied):
        unlike = text[a[tied] + k] != text[b[tied] + k]
        differs[tied[unlike]] = True
        k += 1
        tied = tied[~unlike]
        tied = tied[size[tied] > k]
    return np.concatenate([[0], np.cumsum(differs)])


def suffix_array(text: np.ndarray) -> np.ndarray:
    """Starts of all suffixes of a string of non-negative integers, in order."""
    n = len(text)
    if n < 2:
        return np.arange(n)
    symbols = int(text.max()) + 1
    _induce = _induce_small if symbols <= SMALL_ALPHABET else _induce_large
    ends = np.cumsum(np.bincount(text, minlength=symbols))
    smaller = classify(text)
    lms = leftmost_smaller(smaller)
    if not len(lms):
        return _induce(text, smaller, lms, ends)
    first = lms[np.argsort(text[lms], kind="stable")]
    sorted_ = _induce(text, smaller, first, ends)
    is_lms = np.zeros(n, bool)
    is_lms[lms] = True
    order = sorted_[is_lms[sorted_]]
    name = np.empty(n, np.int64)
    name[order] = _names(text, order, lms)
    reduced = name[lms]
    deeper = np.argsort(reduced) if int(reduced.max()) + 1 == len(lms) else suffix_array(reduced)
    return _induce(text, smaller, lms[deeper], ends)


def permuted_common_prefixes(text: bytes, order: np.ndarray, most: int) -> np.ndarray:
    """For each position, in text order, the length of the common prefix with its predecessor in the
    suffix array, up to `most`. Compared eight bytes at a time, over what still agrees."""
    n = len(text)
    before = np.empty(n, np.int64)
    before[order[1:]] = order[:-1]
    before[order[0]] = n
    padded = np.frombuffer(text + b"\x00" * (most + 16), np.uint8)
    words = np.lib.stride_tricks.sliding_window_view(padded, 8)[: n + most + 8].copy().view("<u8").ravel()
    out = np.zeros(n, np.int64)
    live = np.flatnonzero(before < n)
    for k in range(0, most, 8):
        xor = words[live + k] ^ words[before[live] + k]
        same = xor == 0
        low = xor & (~xor + np.uint64(1))
        out[live] += np.where(same, 8, np.log2(np.where(same, 1, low).astype(np.float64)).astype(np.int64) // 8)
        live = live[same]
    room = n - np.maximum(np.arange(n), before)
    return np.minimum(np.minimum(out, most), np.maximum(room, 0))
