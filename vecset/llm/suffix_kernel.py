"""Kernels of suffix-array dedup: window owners, and the two-stage suffix sort of a byte string."""

from __future__ import annotations

import functools

import numpy as np

from .common import mix64

#: An odd multiplier and its inverse modulo 2^64.
BASE = 0x9E3779B97F4A7C15
UNBASE = pow(BASE, -1, 1 << 64)
GRAM = 48


def powers(base: int, n: int) -> np.ndarray:
    """base^0 .. base^(n-1) modulo 2^64."""
    return _powers(base, 1 << max(12, (n - 1).bit_length()))[:n] if n <= 1 << 20 else _powers.__wrapped__(base, n)


@functools.cache
def _powers(base: int, n: int) -> np.ndarray:
    out = np.ones(max(n, 1), np.uint64)
    have = 1
    with np.errstate(over="ignore"):
        while have < n:
            more = min(have, n - have)
            out[have : have + more] = out[:more] * np.uint64(pow(base, have, 1 << 64))
            have += more
    return out[:n]


def owners(flat: np.ndarray, off: np.ndarray, width: int) -> tuple[np.ndarray, ...]:
    """Runs of windows of `width` bytes that share an owner, in the texts flat[off[i]:off[i + 1]].

    A window's owner is its gram with the least hash, the first of equal ones. So equal windows have owners of equal hash at the
    same place. Returns (text, hash of the owner, owner's place less the first window, first, last window, hash of the run's bytes).
    """
    gram = min(GRAM, width)
    n = len(flat)
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, np.int64, np.int64))
    if n < width:
        return none
    with np.errstate(over="ignore"):
        up, down = powers(BASE, n + 1), powers(UNBASE, n + 1)
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((flat.astype(np.uint64) + np.uint64(1)) * up[:n], out=total[1:])
        gh = mix64((total[gram:] - total[:-gram]) * down[: n + 1 - gram])
        places = np.uint64(max(n.bit_length(), 1))
        key = (gh >> places << places) | np.arange(len(gh), dtype=np.uint64)
        span = width - gram + 1
        low = _sliding_min(key, span)
        mask = (np.uint64(1) << places) - np.uint64(1)
        own = (low & mask).astype(np.int64)
        text = np.searchsorted(off, np.arange(len(own)), "right") - 1
        ok = np.arange(len(own)) + width <= off[text + 1]
        at = np.flatnonzero(ok)
        if not len(at):
            return none
        cut = np.flatnonzero((np.diff(own[at]) != 0) | (np.diff(at) != 1) | (np.diff(text[at]) != 0)) + 1
        first = at[np.concatenate(([0], cut))]
        last = at[np.concatenate((cut - 1, [len(at) - 1]))]
        t, o = text[first], own[first]
        whole = mix64((total[last + width] - total[first]) * down[first] + (last - first).astype(np.uint64) * np.uint64(BASE))
    return t, gh[o].view(np.int64), o - first, first - off[t], last - off[t], whole.view(np.int64)


def _sliding_min(x: np.ndarray, span: int) -> np.ndarray:
    n = len(x) - span + 1
    pad = -len(x) % span
    blocks = np.concatenate((x, np.full(pad, np.iinfo(np.uint64).max, np.uint64))).reshape(-1, span)
    left = np.minimum.accumulate(blocks, axis=1).ravel()
    right = np.minimum.accumulate(blocks[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(right[:n], left[span - 1 : span - 1 + n])


def smaller_than_next(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than the one after it; the empty suffix is the least."""
    n = len(text)
    head = np.concatenate(([0], np.flatnonzero(np.diff(text)) + 1))
    run = np.repeat(np.arange(len(head)), np.diff(np.append(head, n)))
    up = np.append(text[head[1:]] > text[head[:-1]], False)
    return up[run]


def _rows(padded: np.ndarray, at: np.ndarray) -> np.ndarray:
    """64 bytes from each place, as 8 words."""
    return np.lib.stride_tricks.sliding_window_view(padded, 64)[at].view(np.uint64).reshape(len(at), 8)


def _same_as_previous(padded: np.ndarray, at: np.ndarray, block: int = 1 << 16) -> np.ndarray:
    """Whether the 64 bytes at each place equal those at the place before it in the list."""
    out = np.zeros(len(at), bool)
    for a in range(1, len(at), block):
        rows = _rows(padded, at[a - 1 : a + block])
        out[a : a + block] = (rows[1:] == rows[:-1]).all(axis=1)[: len(out[a : a + block])]
    return out


def sort_direct(padded: np.ndarray, at: np.ndarray, depth: int) -> np.ndarray:
    """Places sorted by at least `depth` bytes from each: by 8 bytes, then groups of ties by 64 more at a time. Groups whose members
    agree in the next 64 bytes are passed over without a sort."""
    if not len(at):
        return at
    key = np.zeros(len(at), np.uint64)
    for j in range(8):
        key = key << np.uint64(8) | padded[at + j].astype(np.uint64)
    order = np.argsort(key, kind="stable")
    at, key = at[order], key[order]
    new = np.concatenate(([True], key[1:] != key[:-1]))
    del key, order
    for d in range(8, depth, 64):
        tied = np.flatnonzero(~new | np.append(~new[1:], False))
        if not len(tied):
            break
        same = _same_as_previous(padded, at[tied] + d)
        first = new[tied]
        group = np.cumsum(first) - 1
        mixed = np.zeros(group[-1] + 1, bool)
        mixed[group[~first & ~same]] = True
        todo = np.flatnonzero(mixed[group])
        for a, b in _group_blocks(group[todo], 1 << 18):
            sub = todo[a:b]
            rows = _rows(padded, at[tied[sub]] + d).byteswap()
            order = np.lexsort((*(rows[:, k] for k in range(7, -1, -1)), group[sub]))
            slots, rows = tied[sub], rows[order]
            at[slots] = at[slots][order]
            new[slots[1:]] |= (rows[1:] != rows[:-1]).any(axis=1)
    return at


def _group_blocks(group: np.ndarray, most: int):
    """Cuts of a sorted array between groups, about `most` apart."""
    a = 0
    while a < len(group):
        b = min(a + most, len(group))
        if b < len(group):
            low = int(np.searchsorted(group, group[b], "left"))
            b = low if low > a else int(np.searchsorted(group, group[b], "right"))
        yield a, b
        a = b


def suffix_array(text: np.ndarray, depth: int) -> np.ndarray:
    """All suffixes of text in the order of at least their first `depth` bytes, by two stages.

    Suffixes smaller than their successor are sorted directly. Each other suffix is one byte before a suffix that is smaller, so a
    scan over the buckets of first bytes, in order, appends it to its bucket when its successor comes by.
    """
    n = len(text)
    if not n:
        return np.zeros(0, np.int64)
    padded = np.concatenate((text, np.zeros(depth + 136, np.uint8)))
    small = smaller_than_next(text)
    direct = sort_direct(padded, np.flatnonzero(small), depth)
    edge = np.searchsorted(text[direct], np.arange(257))
    induced: list[list[np.ndarray]] = [[] for _ in range(256)]
    induced[text[n - 1]].append(np.array([n - 1]))
    out = []

    def scan(places: np.ndarray, c: int) -> np.ndarray:
        """Hands the larger predecessors of these places to their buckets; returns those of bucket c itself."""
        prev = places[places > 0] - 1
        prev = prev[~small[prev]]
        first = text[prev]
        order = np.argsort(first, kind="stable")
        prev, first = prev[order], first[order]
        cut = np.flatnonzero(np.diff(first)) + 1
        own = prev[:0]
        for part in np.split(prev, cut) if len(prev) else []:
            if text[part[0]] == c:
                own = part
            else:
                induced[text[part[0]]].append(part)
        return own

    for c in range(256):
        wave = np.concatenate(induced[c]) if induced[c] else direct[:0]
        while len(wave):
            out.append(wave)
            wave = scan(wave, c)
        own = direct[edge[c] : edge[c + 1]]
        if len(own):
            out.append(own)
            scan(own, c)
    return np.concatenate(out)


def common_prefix_reaches(text: np.ndarray, order: np.ndarray, width: int) -> np.ndarray:
    """Whether each suffix shares its first `width` bytes with the one before it in order. Ends of the text count as zero bytes."""
    padded = np.concatenate((text, np.zeros(width + 136, np.uint8)))
    live = np.arange(1, len(order))
    for d in range(0, width, 64):
        step = min(d, max(0, width - 64))
        if not len(live):
            break
        if width >= 64:
            ok = np.zeros(len(live), bool)
            for a in range(0, len(live), 1 << 16):
                k = live[a : a + (1 << 16)]
                ok[a : a + (1 << 16)] = (_rows(padded, order[k] + step) == _rows(padded, order[k - 1] + step)).all(axis=1)
        else:
            ok = np.ones(len(live), bool)
            for j in range(width):
                ok &= padded[order[live] + j] == padded[order[live - 1] + j]
        live = live[ok]
    out = np.zeros(len(order), bool)
    out[live] = True
    return out


def repeated_windows(segments: list[np.ndarray], copies: np.ndarray, width: int) -> list[np.ndarray]:
    """For each segment, which of its windows of `width` bytes start anywhere else: in another segment, elsewhere in the same, or
    in a copy of the segment."""
    size = np.array([len(s) for s in segments], np.int64)
    text = np.concatenate(segments) if segments else np.zeros(0, np.uint8)
    ends = np.cumsum(size)
    own = np.repeat(np.arange(len(size)), size)
    window = np.arange(len(text)) + width <= ends[own]
    order = suffix_array(text, width)
    run = np.cumsum(~common_prefix_reaches(text, order, width)) - 1
    weight = np.where(window, copies[own], 0)[order]
    many = np.zeros(len(text), bool)
    many[order] = (np.bincount(run, weights=weight, minlength=1) >= 2)[run] if len(run) else False
    many &= window
    return [many[e - s : max(e - s, e - width + 1)] for s, e in zip(size, ends, strict=True)]


def may_repeat(segments: list[np.ndarray], owner: np.ndarray, rel: np.ndarray, copies: np.ndarray, width: int, parts: int = 8) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(segment, first window, end) of the runs of windows that may start in two segments; no other window does.

    Equal windows have equal owners at the same place. The places are dealt in `parts` ranges; all windows of a range share the bytes
    around the owner, its core. A range of a segment stays if another segment of that owner has the same hash of that core, and one of
    those that have it has no copy (windows of copies are known to repeat). owner: its hash; rel: its place in the first window.
    """
    size = np.array([len(s) for s in segments], np.int64)
    text, many = np.concatenate(segments), size - width + 1
    places = width - min(GRAM, width) + 1
    low = np.arange(0, places, -(-places // parts))
    high = np.append(low[1:], places) - 1
    row, part = np.nonzero((rel[:, None] >= low) & (rel[:, None] - many[:, None] < high))
    row, part = row[::-1], part[::-1]
    order = np.argsort(row, kind="stable")  # by segment, the last range first: its windows come first
    row, part = row[order], part[order]
    with np.errstate(over="ignore"):
        total = np.concatenate((np.zeros(1, np.uint64), np.cumsum((text.astype(np.uint64) + np.uint64(1)) * powers(BASE, len(text)))))
        at = (np.cumsum(size) - size + rel)[row] - low[part]
        core = (total[at + width - (high - low)[part]] - total[at]) * powers(UNBASE, len(text) + 1)[at]
        key = mix64(mix64(core) ^ mix64(owner.view(np.uint64)[row] + part.astype(np.uint64)))
    _, kind, n = np.unique(key, return_inverse=True, return_counts=True)
    stays = ((n > 1) & (np.bincount(kind, weights=copies[row] == 1) > 0))[kind]
    row, part = row[stays], part[stays]
    first, end = np.maximum(rel[row] - high[part], 0), np.minimum(rel[row] - low[part] + 1, many[row])
    new = np.append(True, (row[1:] != row[:-1]) | (first[1:] != end[:-1]))[: len(row)]
    return row[new], first[new], end[np.append(new[1:], True)[: len(row)]]
