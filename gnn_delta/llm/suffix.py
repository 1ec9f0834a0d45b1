"""Suffix array by external induced sorting, with capped common-prefix values.

Suffixes are S-type (smaller than the next suffix) or L-type. The leftmost S-type suffixes (LMS) are
sorted, by recursion on the string of their names, and induce all others: a scan in order puts the
predecessor of each suffix into the queue of its first sign. The queues form a priority queue over
(first sign, order of arrival): what a later bucket will need waits in first-in-first-out runs, which go
to files when the resident part exceeds a limit. Whole buckets are scanned at once with NumPy. Entries
carry the length of the prefix they share with the entry before them in their queue: one more than the
least common prefix between their two inducers, found in a table of minima over the scanned batch.
"""

from __future__ import annotations

import tempfile

import numpy as np

SEPARATOR, FIRST = 1, 2  # sign 0 ends the text, 1 stands between texts, byte b is b + 2
SIGNS = 258


class Queues:
    """First-in-first-out runs of (position, common prefix) per sign; runs beyond ``limit`` bytes go to disk."""

    def __init__(self, limit: int):
        self.runs: list[list] = [[] for _ in range(SIGNS)]
        self.least = np.full(SIGNS, 255, dtype=np.uint8)  # least common prefix since the last entry
        self.fresh = np.ones(SIGNS, dtype=bool)
        self.limit, self.resident = limit, 0
        self.file = None

    def put(self, sign: int, position: np.ndarray, common: np.ndarray) -> None:
        size = position.nbytes + common.nbytes
        if self.resident + size > self.limit:
            self.file = self.file or tempfile.TemporaryFile()
            self.file.seek(0, 2)
            at = self.file.tell()
            position.tofile(self.file)
            common.tofile(self.file)
            self.runs[sign].append((at, len(position)))
        else:
            self.resident += size
            self.runs[sign].append((position, common))

    def take(self, sign: int) -> tuple[np.ndarray, np.ndarray]:
        positions, commons = [], []
        for a, b in self.runs[sign]:
            if isinstance(b, int):
                self.file.seek(a)
                a, b = np.fromfile(self.file, np.int32, b), np.fromfile(self.file, np.uint8, b)
            else:
                self.resident -= a.nbytes + b.nbytes
            positions.append(a)
            commons.append(b)
        self.runs[sign] = []
        if not positions:
            return np.zeros(0, np.int32), np.zeros(0, np.uint8)
        return np.concatenate(positions), np.concatenate(commons)

    def close(self) -> None:
        if self.file is not None:
            self.file.close()


def common_prefix(text: np.ndarray, a: np.ndarray, b: np.ndarray, cap: int) -> np.ndarray:
    """Length, up to ``cap``, of the prefixes that suffixes a and b share, compared four signs at a time.

    Different suffixes differ at the end sign at the latest, so the padding is never compared."""
    padded = np.concatenate([text, np.zeros(4, np.uint16)])
    words = np.ndarray(shape=(len(text),), dtype="<u8", buffer=padded, strides=(2,))
    out = np.full(len(a), cap, dtype=np.int64)
    alive = np.arange(len(a))
    for k in range(0, cap, 4):
        apart = words[a[alive] + k] ^ words[b[alive] + k]
        ended = np.flatnonzero(apart)
        x = apart[ended]
        out[alive[ended]] = k + np.bitwise_count((x - np.uint64(1)) & ~x) // 16
        alive = np.delete(alive, ended)
        if not len(alive):
            break
    return np.minimum(out, cap).astype(np.uint8)


def minima(common: np.ndarray) -> list[np.ndarray]:
    """Table of minima over stretches of 1, 2, 4, ... values."""
    table, span = [common], 1
    while 2 * span <= len(common):
        table.append(np.minimum(table[-1][:-span], table[-1][span:]))
        span *= 2
    return table


def least_between(table: list[np.ndarray], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """Minimum of the values at left..right (both included, left <= right)."""
    length = right - left + 1
    level = np.frexp(length)[1] - 1
    out = np.empty(len(left), dtype=np.uint8)
    for k in np.unique(level):
        at = np.flatnonzero(level == k)
        out[at] = np.minimum(table[k][left[at]], table[k][right[at] - (1 << int(k)) + 1])
    return out


def feed(queues: Queues, text: np.ndarray, scanned: np.ndarray, common: np.ndarray, chosen: np.ndarray, cap: int) -> None:
    """Put the predecessors of the ``chosen`` scanned suffixes into the queues of their first signs.

    ``common[i]`` is what suffix i of the scan shares with the one scanned before it."""
    if not len(scanned):
        return
    if cap == 0:  # order only
        where = np.flatnonzero(chosen)
        sign = text[scanned[where] - 1]
        order = np.argsort(sign, kind="stable")
        where, sign = where[order], sign[order]
        heads = np.flatnonzero(np.concatenate([[True], sign[1:] != sign[:-1]])) if len(where) else where
        for s, a, b in zip(sign[heads].tolist(), heads.tolist(), [*heads[1:].tolist(), len(where)], strict=False):
            queues.put(s, (scanned[where[a:b]] - 1).astype(np.int32), np.zeros(b - a, np.uint8))
        return
    table = minima(common)
    whole = table[-1].min()
    where = np.flatnonzero(chosen)
    sign = text[scanned[where] - 1]
    order = np.argsort(sign, kind="stable")
    where, sign = where[order], sign[order]
    touched = np.zeros(SIGNS, dtype=bool)
    if len(where):
        first = np.concatenate([[True], sign[1:] != sign[:-1]])
        left = np.concatenate([[0], where[:-1] + 1])
        left[first] = 0
        shared = least_between(table, left, where)
        heads = np.flatnonzero(first)
        kinds = sign[heads]
        shared[heads] = np.minimum(shared[heads], queues.least[kinds])
        value = np.minimum(shared.astype(np.int64) + 1, cap).astype(np.uint8)
        value[heads[queues.fresh[kinds]]] = 0
        ends = np.concatenate([heads[1:], [len(where)]])
        for s, a, b in zip(kinds.tolist(), heads.tolist(), ends.tolist(), strict=True):
            queues.put(s, (scanned[where[a:b]] - 1).astype(np.int32), value[a:b])
            rest = where[b - 1] + 1
            queues.least[s] = 255 if rest == len(common) else least_between(table, np.array([rest]), np.array([len(common) - 1]))[0]
            touched[s] = True
        queues.fresh[kinds] = False
    queues.least[~touched] = np.minimum(queues.least[~touched], whole)


def induce(text: np.ndarray, small: np.ndarray, lms: np.ndarray, lms_common: np.ndarray, cap: int, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """All suffixes in order, and the common prefix of each with the one before it, from sorted LMS suffixes."""
    lms_sign = text[lms]
    seeds = np.searchsorted(lms_sign, np.arange(SIGNS + 1))
    large: list[tuple[np.ndarray, np.ndarray]] = []
    queues = Queues(limit)
    before = -1  # the suffix scanned last
    for sign in range(SIGNS):
        positions, commons = [], []
        while True:
            position, common = queues.take(sign)
            if not len(position):
                break
            positions.append(position)
            commons.append(common)
            common = common.copy()
            common[0] = common[0] if before >= 0 and text[before] == sign else 0
            chosen = (position > 0) & ~small[position - 1]
            feed(queues, text, position, common, chosen, cap)
            before = int(position[-1])
        none = (np.zeros(0, np.int32), np.zeros(0, np.uint8))
        large.append((np.concatenate(positions), np.concatenate(commons)) if positions else none)
        a, b = seeds[sign], seeds[sign + 1]
        if b > a:
            position, common = lms[a:b], lms_common[a:b].copy()
            common[0] = common_prefix(text, np.array([before]), position[:1], cap)[0] if before >= 0 and text[before] == sign else 0
            feed(queues, text, position, common, position > 0, cap)
            before = int(position[-1])
    queues.close()

    parts: list[tuple[np.ndarray, np.ndarray]] = []
    queues = Queues(limit)
    before = -1
    for sign in range(SIGNS - 1, -1, -1):
        positions, commons = [], []
        while True:
            position, common = queues.take(sign)
            if not len(position):
                break
            positions.append(position)
            commons.append(common)
            common = common.copy()
            common[0] = common[0] if before >= 0 and text[before] == sign else 0
            feed(queues, text, position, common, (position > 0) & small[position - 1], cap)
            before = int(position[-1])
        up_position, up_common = large[sign]
        if len(up_position):
            down = up_position[::-1]
            common = np.concatenate([[0], up_common[:0:-1]]).astype(np.uint8)
            if before >= 0 and text[before] == sign:
                common[0] = common_prefix(text, np.array([before]), down[:1], cap)[0]
            border = common[0]
            chosen = (down > 0) & small[down - 1]
            feed(queues, text, down, common, chosen, cap)
            before = int(down[-1])
        else:
            border = np.uint8(0)
        if positions:
            down, common = np.concatenate(positions), np.concatenate(commons)
            # in rising order a suffix shares with the one below it what that one carried
            rising = np.concatenate([common[1:], [border]])[::-1].astype(np.uint8)
            parts.append((down[::-1], rising))
        if len(up_position):
            up = up_common.copy()
            up[0] = 0
            parts.append((up_position, up))
        if sign == 0:
            parts.append((np.array([len(text) - 1], np.int32), np.zeros(1, np.uint8)))
    queues.close()
    parts.reverse()
    return np.concatenate([p for p, _ in parts]), np.concatenate([c for _, c in parts])


def types(text: np.ndarray) -> np.ndarray:
    """Whether each suffix is S-type; the end sign is."""
    n = len(text)
    change = np.flatnonzero(text[1:] != text[:-1])
    following = np.searchsorted(change, np.arange(n))
    small = np.ones(n, dtype=bool)
    inner = following < len(change)
    at = change[following[inner]]
    small[inner] = text[at + 1] > text[at]
    return small


def ranks_of_names(names: np.ndarray, enough: int) -> np.ndarray:
    """Order of the suffixes of a string of names by their first ``enough`` names (ties by position).

    The recursion works on whole stretches of names: ranks of stretches are packed, as many as fit 62 bits,
    into keys of longer stretches, which are ranked in turn."""
    rank, span, n = names.astype(np.int64) + 1, 1, len(names)
    while True:
        bits = int(rank.max()).bit_length()
        pack = max(2, 62 // bits)
        key = rank.copy()
        for k in range(1, pack):
            key <<= bits
            if k * span < n:
                key[: n - k * span] |= rank[k * span :]
        order = np.argsort(key)
        sorted_key = key[order]
        step = np.concatenate([[1], 1 + np.cumsum(sorted_key[1:] != sorted_key[:-1])])
        rank = np.empty(n, dtype=np.int64)
        rank[order] = step
        span *= pack
        if step[-1] == n or span >= min(n, enough):
            return np.lexsort((np.arange(n), rank)) if step[-1] < n else order


def suffix_array(text: np.ndarray, cap: int, limit: int = 64 << 20) -> tuple[np.ndarray, np.ndarray]:
    """Suffixes of ``text`` (signs, ending with the only 0) in order of their first ``cap`` signs, with common
    prefixes up to ``cap`` (under 255)."""
    text = np.asarray(text, dtype=np.uint16)  # 16-bit signs sort by radix
    if len(text) == 1:
        return np.zeros(1, np.int32), np.zeros(1, np.uint8)
    small = types(text)
    lms = np.flatnonzero(small[1:] & ~small[:-1]) + 1
    if not len(lms):
        lms = np.array([len(text) - 1])
    # sort the LMS substrings by induction from any order, name them, sort the string of names
    start = lms[np.argsort(text[lms], kind="stable")]
    rough, _ = induce(text, small, start.astype(np.int32), np.zeros(len(lms), np.uint8), 0, limit)
    is_lms = np.zeros(len(text) + 1, dtype=bool)
    is_lms[lms] = True
    ordered = rough[is_lms[rough]]
    place = np.zeros(len(text), dtype=np.int64)
    place[lms] = np.arange(len(lms))
    after = np.append(lms[1:], len(text) - 1)
    length = (after - lms)[place[ordered]] + 1
    differs = np.concatenate([[True], ~equal_pieces(text, ordered[:-1], ordered[1:], length[:-1], length[1:])])
    name = np.cumsum(differs) - 1
    names = np.empty(len(lms), dtype=np.int64)
    names[place[ordered]] = name
    order = lms[ranks_of_names(names, cap)] if name[-1] < len(lms) - 1 else ordered
    common = np.zeros(len(order), np.uint8)
    common[1:] = common_prefix(text, order[:-1].astype(np.int64), order[1:].astype(np.int64), cap)
    return induce(text, small, order.astype(np.int32), common, cap, limit)


def equal_pieces(text: np.ndarray, a: np.ndarray, b: np.ndarray, a_len: np.ndarray, b_len: np.ndarray) -> np.ndarray:
    same = a_len == b_len
    alive = np.flatnonzero(same)
    k = 0
    while len(alive):
        equal = text[a[alive] + k] == text[b[alive] + k]
        same[alive[~equal]] = False
        k += 1
        alive = alive[equal & (a_len[alive] > k)]
    return same
