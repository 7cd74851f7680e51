"""Suffix order of many byte strings by prefix-free parsing.

A rolling hash over ``TRIGGER`` bytes ends a phrase wherever it is 0 modulo
``EVERY``; the next phrase starts with the same trigger bytes.  No suffix of a
phrase longer than the trigger is then a prefix of another, so the order of all
text suffixes follows from two small suffix arrays: that of the dictionary of
distinct phrases and that of the parse, the strings as sequences of phrase
ranks.  Repetitive input has a small dictionary, however long it is.

Both arrays are built by prefix doubling.  ``depth`` stops it once that many
symbols are told apart; suffixes that agree so far may then stand in any order.
"""

from __future__ import annotations

import numpy as np

from stalegrad.llm.kernels import U64, byte_codes, windows_hash

TRIGGER, EVERY = 8, 32


def _dense(keys: np.ndarray) -> tuple[np.ndarray, int]:
    order = np.argsort(keys)
    ordered = keys[order]
    step = np.empty(len(keys), dtype=np.int64)
    step[:1] = 0
    np.cumsum(ordered[1:] != ordered[:-1], out=step[1:])
    rank = np.empty(len(keys), dtype=np.int64)
    rank[order] = step
    return rank, int(step[-1]) + 1 if len(keys) else 0


def suffix_ranks(symbols: np.ndarray, last: np.ndarray, pack: int, base: int, depth: int | None) -> np.ndarray:
    """Rank of each suffix symbols[i : last[i] + 1]; equal suffixes have equal ranks.

    ``last`` is the place of the final symbol of the string that holds i;
    symbols are positive and below ``base``, and base ** pack fits 63 bits.
    """
    n = len(symbols)
    here = np.arange(n)
    key = np.zeros(n, dtype=np.int64)
    for j in range(pack):
        at = here + j
        inside = at <= last
        key = key * base + np.where(inside, symbols[np.minimum(at, n - 1)], 0)
    rank, classes = _dense(key)
    h = pack
    while classes < n and (depth is None or h < depth):
        at = here + h
        inside = at <= last
        if not inside.any():
            break
        rank, now = _dense(rank * (classes + 1) + np.where(inside, rank[np.minimum(at, n - 1)] + 1, 0))
        if now == classes:
            break
        classes, h = now, h * 2
    return rank


def suffix_keys(data: np.ndarray, offs: np.ndarray, depth: int | None = None, wanted: np.ndarray | None = None) -> np.ndarray:
    """An integer for each byte place, ordered as the suffixes that start there.

    The suffix ends with its own string; strings are data[offs[k]:offs[k + 1]].
    With ``wanted`` (places) only those get keys, and the dictionary's suffix
    array leaves out phrases in which none of them starts.
    """
    n = len(data)
    if wanted is None:
        wanted = np.arange(n)
    if not len(wanted):
        return np.zeros(0, dtype=np.int64)
    ends = offs[1:]
    owner = np.repeat(np.arange(len(ends)), np.diff(offs))
    hashes = windows_hash(byte_codes(2)[data], TRIGGER)
    cut = np.flatnonzero(hashes & U64(EVERY - 1) == 0)
    cut = cut[owner[cut] == owner[np.minimum(cut + TRIGGER - 1, n - 1)]]  # trigger windows inside one string
    begins = np.union1d(offs[:-1][np.diff(offs) > 0], cut)
    whose = owner[begins]
    final = np.append(whose[1:] != whose[:-1], True)
    stops = np.where(final, ends[whose], np.append(begins[1:], n) + TRIGGER)

    raw = data.tobytes()
    seen: dict[bytes, int] = {}
    mark = (b"\2", b"\1")  # how the string's end and a phrase's end differ
    phrase = np.fromiter((seen.setdefault(raw[a:b] + mark[f], len(seen)) for a, b, f in zip(begins.tolist(), stops.tolist(), final.tolist(), strict=True)), dtype=np.int64, count=len(begins))

    # the parse: phrases by rank; a phrase that ends its string comes before its continuations
    listed = list(seen)
    order = sorted(range(len(listed)), key=lambda i: (listed[i][:-1], listed[i][-1]))
    rank = np.empty(len(listed), dtype=np.int64)
    rank[order] = np.arange(1, len(listed) + 1)
    parse = rank[phrase]
    last_phrase = np.flatnonzero(final)[np.searchsorted(np.flatnonzero(final), np.arange(len(begins)))]
    p_rank = suffix_ranks(parse, last_phrase, 1, int(parse.max()) + 2, depth)
    follow = np.where(final, 0, np.append(p_rank[1:], 0) + 1)

    # the dictionary: suffixes of the phrases in which a wanted place lies
    mine = np.searchsorted(begins, wanted, side="right") - 1
    used = np.zeros(len(listed), dtype=bool)
    used[phrase[mine]] = True
    kept = np.flatnonzero(used)
    sizes = np.fromiter((len(listed[i]) for i in kept), dtype=np.int64, count=len(kept))
    at = np.concatenate(([0], np.cumsum(sizes)))
    symbols = np.frombuffer(b"".join([listed[i] for i in kept]), dtype=np.uint8).astype(np.int64) + 3
    symbols[at[1:] - 1] -= 3  # ends sort first
    d_rank = suffix_ranks(symbols, np.repeat(at[1:] - 1, sizes), 7, 259, depth)
    place = np.empty(len(listed), dtype=np.int64)
    place[kept] = at[:-1]
    return d_rank[place[phrase[mine]] + wanted - begins[mine]] * (int(follow.max()) + 1) + follow[mine]


def suffix_order(data: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Places of all suffixes in order (a suffix array over many strings)."""
    return np.argsort(suffix_keys(data, offs), kind="stable")


def common_prefix(data: np.ndarray, a: np.ndarray, b: np.ndarray, width: int) -> np.ndarray:
    """Whether the ``width`` bytes at a and at b are the same, for pairs sorted by a.

    Neighbouring places mostly have neighbouring partners, so runs of pairs with
    one distance are compared once, byte by byte: a pair agrees if no byte of its
    window differs.
    """
    if not len(a):
        return np.zeros(0, dtype=bool)
    cut = np.concatenate(([True], (a[1:] != a[:-1] + 1) | (b[1:] != b[:-1] + 1)))
    first = np.flatnonzero(cut)
    count = np.diff(np.append(first, len(a)))
    span = count + width - 1  # bytes that a run of pairs looks at
    base = np.concatenate(([0], np.cumsum(span)))
    out = np.empty(len(a), dtype=bool)
    for lo in range(0, len(first), 1 << 12):  # some thousand runs at a time
        hi = min(lo + (1 << 12), len(first))
        inside = np.arange(base[hi] - base[lo]) - np.repeat(base[lo:hi] - base[lo], span[lo:hi])
        differ = data[np.repeat(a[first[lo:hi]], span[lo:hi]) + inside] != data[np.repeat(b[first[lo:hi]], span[lo:hi]) + inside]
        seen = np.concatenate(([0], np.cumsum(differ)))
        pair = np.arange(first[lo], first[hi - 1] + count[hi - 1])
        at = np.repeat(base[lo:hi] - base[lo], count[lo:hi]) + pair - np.repeat(first[lo:hi], count[lo:hi])
        out[pair] = seen[at + width] == seen[at]
    return out


def repeated_starts(data: np.ndarray, offs: np.ndarray, width: int) -> np.ndarray:
    """True at every place whose next ``width`` bytes (inside its string) also start elsewhere.

    In suffix order the nearest relative of a suffix is a neighbour, so only
    neighbours are compared, by their bytes; a hash of the window passes over
    neighbours that differ anyway.
    """
    out = np.zeros(len(data), dtype=bool)
    if len(data) < width:
        return out
    room = np.repeat(offs[1:], np.diff(offs)) - np.arange(len(data)) >= width
    starts = np.flatnonzero(room)
    if len(starts) < 2:
        return out
    order = starts[np.argsort(suffix_keys(data, offs, width, starts))]
    prints = windows_hash(byte_codes(0)[data], width)[order]
    same = np.flatnonzero(prints[1:] == prints[:-1])
    left, right = order[same], order[same + 1]
    by_place = np.argsort(left)
    left, right = left[by_place], right[by_place]
    twins = common_prefix(data, left, right, width)
    out[left[twins]] = True
    out[right[twins]] = True
    return out
