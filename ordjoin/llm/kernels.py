"""Vectorised hashing of words and bytes, rolling hashes and content-chosen triggers (numpy only)."""

from __future__ import annotations

import numpy as np

U64 = np.uint64
_BASE = 0xD1342543DE82EF95  # odd, so that it has an inverse modulo 2**64
_INVERSE = pow(_BASE, -1, 2**64)
_POWERS = [np.ones(1, U64), np.ones(1, U64)]
BYTE_CODES = np.random.Generator(np.random.PCG64(20240229)).integers(1, 2**63, 256, dtype=np.uint64) | U64(1)
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_POSITION_BITS = 26
_AT_ONCE = 1 << 22  # bytes


def mixed(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values (a new array)."""
    x = x ^ (x >> U64(30))
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_POWERS[0]) < n:
        m = max(n, 1 << 19)
        for i, base in enumerate((_BASE, _INVERSE)):
            steps = np.full(m, base, U64)
            steps[0] = 1
            _POWERS[i] = np.cumprod(steps, dtype=U64)
    return _POWERS[0], _POWERS[1]


def prefix_sums(symbols: np.ndarray) -> np.ndarray:
    """Prefix sums of symbol * base**position, modulo 2**64."""
    out = np.zeros(len(symbols) + 1, U64)
    np.cumsum(symbols * _powers(len(symbols))[0][: len(symbols)], out=out[1:], dtype=U64)
    return out


def spans_hash(prefix: np.ndarray, first: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hash of each span [first, end), independent of where it stands."""
    back = _powers(len(prefix))[1]
    return mixed((prefix[end] - prefix[first]) * back[first] + (end - first).astype(U64) * U64(0x9E3779B97F4A7C15))


def rolling(prefix: np.ndarray, width: int) -> np.ndarray:
    """Hash of each window of one width."""
    n = len(prefix) - width
    if n <= 0:
        return np.empty(0, U64)
    back = _powers(len(prefix))[1]
    return mixed((prefix[width:] - prefix[:n]) * back[:n])


def word_spans(raw: np.ndarray, ends: np.ndarray, gap: np.ndarray = SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each word, and the index of each document's first word (one more entry at the end)."""
    if not len(raw):
        return np.empty(0, np.int64), np.empty(0, np.int64), np.zeros(len(ends), np.int64)
    inside = ~gap[raw]
    edge = np.zeros(len(raw) + 1, bool)
    edge[ends] = True
    edge[0] = edge[-1] = True
    before = np.empty(len(raw), bool)
    before[0] = False
    before[1:] = inside[:-1]
    starts = np.flatnonzero(inside & (~before | edge[:-1]))
    after = np.empty(len(raw), bool)
    after[-1] = False
    after[:-1] = inside[1:]
    stops = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, stops, np.searchsorted(starts, ends)


def word_hashes(raw: np.ndarray, starts: np.ndarray, stops: np.ndarray) -> np.ndarray:
    if not len(starts):
        return np.empty(0, U64)
    if len(raw) <= _AT_ONCE:
        return spans_hash(prefix_sums(BYTE_CODES[raw]), starts, stops)
    # word by word the hash does not depend on the place, so a long text is taken in stretches that end between words
    cuts = np.unique(np.append(np.searchsorted(stops, np.arange(0, stops[-1], _AT_ONCE), side="right"), len(starts)))
    some = [(x, y, int(starts[x]), int(stops[y - 1])) for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)]
    if cuts[0]:
        some.insert(0, (0, int(cuts[0]), int(starts[0]), int(stops[cuts[0] - 1])))
    return np.concatenate([spans_hash(prefix_sums(BYTE_CODES[raw[low:high]]), starts[x:y] - low, stops[x:y] - low) for x, y, low, high in some])


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    done, m = 1, x
    while done * 2 <= width:
        m = np.minimum(m[:-done], m[done:])
        done *= 2
    rest = width - done
    return np.minimum(m[:-rest], m[rest:]) if rest else m


def trigger_runs(symbols: np.ndarray, offsets: np.ndarray, window: int, gram: int) -> dict[str, np.ndarray]:
    """Runs of window starts that choose the same trigger.

    A window's trigger is the gram with the least rolling hash in it (the last one on ties), so it depends on the
    window's content alone: equal windows stand at equal places around equal triggers. Per run: document index,
    first window start in the document, number of windows, trigger hash, hash of all symbols that its windows cover.
    """
    n = len(symbols)
    none = {"doc": np.empty(0, np.int64), "start": np.empty(0, np.int64), "n": np.empty(0, np.int64), "key": np.empty(0, U64), "ctx": np.empty(0, U64)}
    if n < window:
        return none
    if n >= 1 << _POSITION_BITS:
        raise ValueError("a slice holds too many symbols")
    prefix = prefix_sums(symbols)
    grams = rolling(prefix, gram)
    low = U64((1 << _POSITION_BITS) - 1)
    order = (grams & ~low) | (low - np.arange(len(grams), dtype=U64))
    least = _sliding_min(order, window - gram + 1)
    at = (low - (least & low)).astype(np.int64)
    room = np.repeat(offsets[1:], np.diff(offsets))[: len(at)] - np.arange(len(at))
    valid = room >= window
    head = valid.copy()
    head[1:] &= ~valid[:-1] | (at[1:] != at[:-1])
    first = np.flatnonzero(head)
    if not len(first):
        return none
    tail = valid.copy()
    tail[:-1] &= ~valid[1:] | (at[1:] != at[:-1])
    last = np.flatnonzero(tail)
    doc = np.searchsorted(offsets, first, side="right") - 1
    return {"doc": doc, "start": first - offsets[doc], "n": last - first + 1, "key": grams[at[first]], "ctx": spans_hash(prefix, first, last + window)}


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)
