"""Edit distances of many strings to one pattern, bit-parallel: a column of the table is two bits per place of the pattern,
held in 64-bit words, and every step works on all strings of a block, or on all of many pairs, at once."""

from __future__ import annotations

import numpy as np

#: Strings of a block: many enough to outweigh the cost of a step, few enough for its arrays to stay in the cache.
BLOCK = 10_000


class Texts:
    """Strings made ready to be compared with one pattern after another."""

    def __init__(self, strings: list[str]):
        self.size = np.array([len(s) for s in strings], np.int64)
        order = np.argsort(-self.size, kind="stable")
        self.blocks = []  # places of the strings, longest first; their characters, a row per place; strings that reach it
        letters = np.arange(256, dtype=np.uint32)
        for at in (order[i : i + BLOCK] for i in range(0, len(order), BLOCK)):
            size = self.size[at]
            padded = "".join([strings[i].ljust(size[0]) for i in at.tolist()]).encode("utf-32-le", "surrogatepass")
            cells = np.frombuffer(padded, np.uint32).reshape(len(at), size[0])
            letters = letters if cells.max(initial=0) < 256 else np.union1d(letters, cells)
            self.blocks.append((at, cells, np.searchsorted(-size, -np.arange(size[0]), "left")))
        self.letters, kind = letters, np.min_scalar_type(len(letters) - 1)
        plain = len(letters) == 256
        self.blocks = [(at, np.ascontiguousarray((cells.astype(kind) if plain else np.searchsorted(letters, cells).astype(kind)).T), reach) for at, cells, reach in self.blocks]

    def distances(self, pattern: str) -> np.ndarray:
        m = len(pattern)
        if not m:
            return self.size.copy()
        letter = np.frombuffer(pattern.encode("utf-32-le", "surrogatepass"), np.uint32)
        place = np.searchsorted(self.letters, letter)
        known = np.flatnonzero((place < len(self.letters)) & (self.letters[np.minimum(place, len(self.letters) - 1)] == letter))
        table = np.zeros(((m + 63) // 64, len(self.letters)), np.uint64)  # places of the pattern that hold a letter
        np.bitwise_or.at(table, (known // 64, place[known]), np.uint64(1) << (known % 64).astype(np.uint64))
        out = np.empty(len(self.size), np.int64)
        for at, cells, reach in self.blocks:
            out[at] = _columns(table, cells, reach, m, len(at))
        return out


def _columns(table: np.ndarray, cells: np.ndarray, reach: np.ndarray, m: int, n: int) -> np.ndarray:
    one, top, last = np.uint64(1), np.uint64(63), np.uint64((m - 1) % 64)
    words = len(table)
    rise, fall = np.full((words, n), ~np.uint64(0)), np.zeros((words, n), np.uint64)  # steps of +1 and -1 down the column
    score = np.full(n, m, np.int64).view(np.uint64)
    space = np.empty((8, n), np.uint64)
    for codes, k in zip(cells, reach.tolist()):
        codes = codes[:k].astype(np.intp)
        eq, xv, xh, ph, mh, up, down, more = (x[:k] for x in space)
        s = score[:k]
        for w in range(words):
            pv, mv = rise[w, :k], fall[w, :k]
            np.take(table[w], codes, out=eq, mode="clip")
            np.bitwise_or(eq, mv, out=xv)
            if w:
                np.bitwise_or(eq, down, out=eq)
            np.bitwise_and(eq, pv, out=xh)
            np.add(xh, pv, out=xh)
            np.bitwise_xor(xh, pv, out=xh)
            np.bitwise_or(xh, eq, out=xh)
            np.bitwise_or(xh, pv, out=ph)
            np.invert(ph, out=ph)
            np.bitwise_or(ph, mv, out=ph)
            np.bitwise_and(pv, xh, out=mh)
            if w == words - 1:
                for x, change in ((ph, np.add), (mh, np.subtract)):
                    np.right_shift(x, last, out=more)
                    np.bitwise_and(more, one, out=more)
                    change(s, more, out=s)
            else:
                np.right_shift(ph, top, out=more)
                np.right_shift(mh, top, out=eq)
            np.left_shift(ph, one, out=ph)
            np.bitwise_or(ph, up if w else one, out=ph)
            np.left_shift(mh, one, out=mh)
            if w:
                np.bitwise_or(mh, down, out=mh)
            np.bitwise_or(xv, ph, out=pv)
            np.invert(pv, out=pv)
            np.bitwise_or(pv, mh, out=pv)
            np.bitwise_and(ph, xv, out=mv)
            if w < words - 1:
                up[:], down[:] = more, eq
    return score.view(np.int64)


#: Pairs that are worked on at once, and bytes of a table of letters.
PAIRS, TABLE = 1 << 16, 16 << 20


class Rows:
    """Strings as rows of letter numbers (from 1, zeros behind the end), forwards and backwards, for ``pair_distances``."""

    def __init__(self, strings: list[str], letters: np.ndarray):
        self.strings, self.letters = strings, len(letters)
        self.size = np.array([len(s) for s in strings], np.int64)
        width = max(8, -(-int(self.size.max(initial=0)) // 8) * 8)
        flat = np.searchsorted(letters, np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), np.uint32)) + 1
        row = np.repeat(np.arange(len(strings)), self.size)
        place = np.arange(len(flat)) - np.repeat(np.cumsum(self.size) - self.size, self.size)
        self.cells = np.zeros((len(strings), width), np.uint8 if len(letters) < 256 else np.uint32)
        back = self.cells.copy()
        self.cells[row, place] = flat
        back[row, self.size[row] - 1 - place] = flat
        self.ahead, self.back = self.cells.view(np.uint64), back.view(np.uint64)

    def table(self, first: int, last: int) -> np.ndarray:
        """Bits of the places, up to 64, of the strings first..last that hold a letter, per string and letter."""
        out = np.zeros((last - first, self.letters + 1), np.uint64)
        for i in range(min(64, int(self.size[first:last].max(initial=0)))):
            at = np.flatnonzero(self.size[first:last] > i)
            out[at, self.cells[first + at, i]] |= np.uint64(1) << np.uint64(i)
        return out.ravel()


def letters_of(strings: list[str]) -> np.ndarray:
    return np.unique(np.frombuffer("".join(strings).encode("utf-32-le", "surrogatepass"), np.uint32))


def _equal_start(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray, cell: int) -> np.ndarray:
    """Equal cells (of so many bytes) at the beginning of rows i of a and rows j of b, a word at a time."""
    out, at = np.zeros(len(i), np.int64), np.arange(len(i))
    for w in range(min(a.shape[1], b.shape[1])):
        x = a[i[at], w] ^ b[j[at], w]
        out[at] += np.bitwise_count((x & (~x + np.uint64(1))) - np.uint64(1)).astype(np.int64) // (8 * cell)
        at = at[x == 0]
        if not len(at):
            break
    return out


def pair_distances(a: Rows, b: Rows, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Edit distances of the pairs (row i of a, row j of b). Both have the same letters.

    What a pair has in common at its beginning and its end is skipped: after k equal letters the column is known
    to go down by one k times and then up."""
    m, n, cell = a.size[i], b.size[j], a.cells.itemsize
    least = np.minimum(m, n)
    k = np.minimum(_equal_start(a.ahead, b.ahead, i, j, cell), least)
    tail = np.minimum(_equal_start(a.back, b.back, i, j, cell), least - k)
    out = np.empty(len(i), np.int64)
    short = m <= 64
    for p in np.unique(i[~short]).tolist():  # patterns beyond a word, each with all of its strings
        at = np.flatnonzero(i == p)
        out[at] = Texts([b.strings[x] for x in j[at].tolist()]).distances(a.strings[p])
    one, step = np.uint64(1), max(1, TABLE // (8 * (a.letters + 1)))
    first = int(i.min(initial=0))
    past = int(i.max(initial=-1)) + 1
    while first < past:
        last = min(past, first + step)
        at = np.flatnonzero(short & (i >= first) & (i < last))
        if len(at):
            steps = (n - tail - k)[at]
            order = np.argsort(-steps, kind="stable")
            at, steps = at[order], steps[order]
            table, flat = a.table(first, last), b.cells.ravel()
            row, end = (i[at] - first) * (a.letters + 1), j[at] * b.cells.shape[1] + (n - tail)[at]
            skipped = k[at].astype(np.uint64)
            low = np.where(skipped < 64, (one << np.minimum(skipped, np.uint64(63))) - one, ~np.uint64(0))
            pv, mv = ~low, low
            reach = np.searchsorted(-steps, -np.arange(steps.max(initial=0), 0, -1), "right")
            for left, c in zip(range(len(reach), 0, -1), reach.tolist()):
                eq = table.take(row[:c] + flat.take(end[:c] - left))
                p, q = pv[:c], mv[:c]
                xv = eq | q
                xh = (((eq & p) + p) ^ p) | eq
                ph = ((q | ~(xh | p)) << one) | one
                mh = (p & xh) << one
                np.bitwise_or(mh, ~(xv | ph), out=p)
                np.bitwise_and(ph, xv, out=q)
            rows = (m - tail)[at].astype(np.uint64)
            held = np.where(rows < 64, (one << np.minimum(rows, np.uint64(63))) - one, ~np.uint64(0))
            out[at] = (n - tail)[at] + np.bitwise_count(pv & held).astype(np.int64) - np.bitwise_count(mv & held)
        first = last
    return out
