"""md5 of many short texts at once, in numpy: the same values as hashing.priority, without a text per row.

A text is a prefix of few different values and an id in decimal, at most 55 bytes together (one block of the hash).
"""

from __future__ import annotations

import numpy as np

_SHIFTS = np.repeat([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]], 4, axis=0).ravel()
_SINES = np.floor(np.abs(np.sin(np.arange(1, 65, dtype=np.float64))) * 2**32).astype(np.uint64).astype(np.uint32)
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)
_CHUNK = 1 << 14  # rows whose words stay in the cache
_POWERS = 10 ** np.arange(19, dtype=np.int64)
_FOUR = np.frombuffer("".join(f"{i:04d}" for i in range(10000)).encode(), "<u4").astype(np.uint64)


def _rounds(words: np.ndarray, used: int, length: int | np.ndarray) -> np.ndarray:
    """The state (4, n) after one block; words (used, n) are the text with its end mark, the others are zero but for the length."""
    bits = 8 * length if isinstance(length, int) else 0
    more = None if isinstance(length, int) else length.astype(np.uint32) << np.uint32(3)
    n = words.shape[1]
    a, b, c, d = (np.full(n, s, np.uint32) for s in _START)
    f, t = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            g = i
            np.bitwise_xor(c, d, out=f)
            np.bitwise_and(f, b, out=f)
            np.bitwise_xor(f, d, out=f)
        elif i < 32:
            g = (5 * i + 1) % 16
            np.bitwise_xor(b, c, out=f)
            np.bitwise_and(f, d, out=f)
            np.bitwise_xor(f, c, out=f)
        elif i < 48:
            g = (3 * i + 5) % 16
            np.bitwise_xor(b, c, out=f)
            np.bitwise_xor(f, d, out=f)
        else:
            g = (7 * i) % 16
            np.invert(d, out=f)
            np.bitwise_or(f, b, out=f)
            np.bitwise_xor(f, c, out=f)
        f += a
        if g < used:
            f += words[g]
        f += np.uint32((int(_SINES[i]) + (bits if g == 14 else 0)) & 0xFFFFFFFF)
        if g == 14 and more is not None:
            f += more
        s = int(_SHIFTS[i])
        np.left_shift(f, np.uint32(s), out=t)
        np.right_shift(f, np.uint32(32 - s), out=f)
        f |= t
        f += b
        a, b, c, d, f = d, f, b, c, a
    return np.stack([a, b, c, d]) + _START[:, None]


def _eight_digits(values: np.ndarray) -> np.ndarray:
    """Eight decimal digits as text, the first one in the lowest byte."""
    upper = values // 10000
    return _FOUR[upper] | _FOUR[values - upper * 10000] << np.uint64(32)


def _put_digits(words: np.ndarray, at: int, values: np.ndarray, digits: int) -> None:
    """Adds the text of values of `digits` decimal digits to the words, from byte `at` on."""
    while digits:
        n = digits % 8 or 8
        scale = 10 ** (digits - n)
        head, values, digits = values // scale, values % scale if digits > n else values, digits - n
        text = _eight_digits(head) >> np.uint64(8 * (8 - n))
        word, bit = at // 4, 8 * (at % 4)
        shifted = text << np.uint64(bit)
        words[word] |= shifted.astype(np.uint32)
        if n * 8 + bit > 32:
            words[word + 1] |= (shifted >> np.uint64(32)).astype(np.uint32)
        if n * 8 + bit > 64:
            words[word + 2] |= (text >> np.uint64(64 - bit)).astype(np.uint32)
        at += n


def digits_of(values: np.ndarray) -> np.ndarray:
    """How many decimal digits each value (not negative) has."""
    return np.maximum(np.searchsorted(_POWERS, values, side="right"), 1)


def priorities(prefixes: list[bytes], which: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Upper and lower 64 bits of md5(prefixes[which[i]] + decimal text of ids[i]); they order as the md5 texts do."""
    high, low = np.empty(len(ids), np.uint64), np.empty(len(ids), np.uint64)
    if not len(ids):
        return high, low
    sizes = np.array([len(p) for p in prefixes])
    width = int(sizes.max()) // 4 * 4 + 4
    table = np.ascontiguousarray(np.frombuffer(b"".join(p.ljust(width, b"\0") for p in prefixes), "<u4").reshape(len(prefixes), -1).T)
    kind = (sizes[which] * 32 + digits_of(np.abs(ids))) * 2 + (ids < 0)
    for k in np.flatnonzero(np.bincount(kind)):
        size, digits, sign = int(k) // 64, int(k) // 2 % 32, int(k) % 2
        length = size + sign + digits
        if length > 55:
            raise ValueError("the text takes more than one block")
        rows, used = np.flatnonzero(kind == k), length // 4 + 1
        for at in range(0, len(rows), _CHUNK):
            mine = rows[at : at + _CHUNK]
            words = np.zeros((used, len(mine)), np.uint32)
            for j in range(-(-size // 4)):
                words[j] = table[j][which[mine]]
            if sign:
                words[size // 4] |= np.uint32(ord("-") << 8 * (size % 4))
            _put_digits(words, size + sign, np.abs(ids[mine]), digits)
            words[length // 4] |= np.uint32(0x80 << 8 * (length % 4))
            a, b, c, d = _rounds(words, used, length).byteswap().astype(np.uint64)
            high[mine], low[mine] = a << np.uint64(32) | b, c << np.uint64(32) | d
    return high, low


def smallest(segments: np.ndarray, n_segments: int, high: np.ndarray, low: np.ndarray, ids: np.ndarray, most: int | None) -> tuple[np.ndarray, np.ndarray]:
    """(rows, ranks): the `most` first of every segment by (high, low, id), with ranks from 0; segments ascend."""
    if n_segments < 1 << 20:  # segment and the upper bits of the hash in one number, which sorts fast
        bits = max(1, int(n_segments - 1).bit_length())
        key = segments.astype(np.uint64) << np.uint64(64 - bits) | high >> np.uint64(bits)
        order = np.argsort(key)
        sorted_key = key[order]
        if (sorted_key[1:] == sorted_key[:-1]).any():
            order = np.lexsort((ids, low, high, segments))
    else:
        order = np.lexsort((ids, low, high, segments))
    seg = segments[order]
    starts = np.searchsorted(seg, np.arange(n_segments))
    ranks = np.arange(len(order)) - starts[seg]
    if most is not None:
        kept = ranks < most
        order, ranks = order[kept], ranks[kept]
    return order, ranks


def texts(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words, lengths): the decimal text of each id with the end mark after it, and its length. One text a column."""
    text = ids.astype("S20")
    lengths = np.char.str_len(text).astype(np.uint8)
    raw = np.zeros((len(ids), 24), np.uint8)
    raw[:, :20] = text.view(np.uint8).reshape(len(ids), 20)
    raw[np.arange(len(ids)), lengths] = 0x80
    return np.ascontiguousarray(raw.view("<u4").T[: int(lengths.max(initial=0)) // 4 + 1]), lengths


def listed(prefixes: list[bytes], which: np.ndarray, words: np.ndarray, lengths: np.ndarray, rows: np.ndarray, lower: bool = False) -> np.ndarray:
    """Upper (or lower) 64 bits of md5(prefixes[which[i]] + the text rows[i] of texts)."""
    out, sizes = np.empty(len(rows), np.uint64), np.array([len(p) for p in prefixes])
    for size in np.unique(sizes).tolist():
        some = None if (sizes == size).all() else np.flatnonzero(sizes[which] == size)
        first, shift = size // 4, 8 * (size % 4)
        table = np.ascontiguousarray(np.frombuffer(b"".join(p.ljust(4 * first + 4, b"\0")[: 4 * first + 4] for p in prefixes), "<u4").reshape(len(prefixes), -1).T)
        for at in range(0, len(rows) if some is None else len(some), 2 * _CHUNK):
            mine = slice(at, at + 2 * _CHUNK) if some is None else some[at : at + 2 * _CHUNK]
            of, row = which[mine], rows[mine]
            length = lengths[row].astype(np.uint32) + np.uint32(size)
            longest = int(length.max())
            if longest > 55:
                raise ValueError("the text takes more than one block")
            block = np.zeros((first + len(words) + 1, len(of)), np.uint32)
            for j in range(first + (shift > 0)):
                block[j] = table[j][of]
            for j, word in enumerate(words):
                text = word[row]
                if shift:
                    block[first + j] |= text << np.uint32(shift)
                    block[first + j + 1] = text >> np.uint32(32 - shift)
                else:
                    block[first + j] = text
            state = _rounds(block, longest // 4 + 1, length)
            upper, rest = state[2 * lower : 2 * lower + 2].byteswap().astype(np.uint64)
            out[mine] = upper << np.uint64(32) | rest
    return out


def first(prefixes: list[bytes], counts: np.ndarray, words: np.ndarray, lengths: np.ndarray, ids: np.ndarray, rows: np.ndarray, most: int | None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(segment, place in rows, rank from 0) of the `most` first of every segment by (md5, id); segment i are the next counts[i] rows."""
    n = len(counts)
    segments = np.repeat(np.arange(n), counts)
    high = listed(prefixes, segments, words, lengths, rows)
    some = np.arange(len(rows))
    if most is not None and len(rows):  # hashes are even: most segments have their first ones below a bound, the others keep all
        share = (most + 4 * most**0.5 + 4) / np.maximum(counts, 1)
        bound = np.where(share < 1, np.minimum(share, 0.999) * 2.0**64, 2.0**64 - 4096).astype(np.uint64)
        below = (high <= bound[segments]) | (share >= 1)[segments]
        short = np.bincount(segments[below], minlength=n) < np.minimum(counts, most)
        some = np.flatnonzero(below | short[segments] if short.any() else below)
    seg, bits = segments[some], max(1, int(n - 1).bit_length())
    key = seg.astype(np.uint64) << np.uint64(64 - bits) | high[some] >> np.uint64(bits)
    order = np.argsort(key)
    key = key[order]
    if (key[1:] == key[:-1]).any():
        low = listed(prefixes, seg, words, lengths, rows[some], True)
        order = np.lexsort((ids[rows[some]], low, high[some], seg))
    seg = seg[order]
    ranks = np.arange(len(seg)) - np.searchsorted(seg, np.arange(n))[seg]
    if most is not None:
        kept = ranks < most
        seg, order, ranks = seg[kept], order[kept], ranks[kept]
    return seg, some[order], ranks
