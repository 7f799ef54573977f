"""Token ids of whole texts by a public byte-level tokenizer, with a bounded table of space-led parts.

The pattern of byte-level BPE starts a new piece at every space that follows a non-white character, so a text may be
cut there and the parts encoded on their own. Parts repeat; each process encodes a part once while it stays in the table.
All parts of some MB of text are looked up at once: a part is named by two 64-bit tabulation hashes of its bytes, the first to
find it, the second to confirm it. The pattern cuts ASCII and Latin letters wherever their kind changes, and no token of the
vocabulary goes over such a cut (looked up once), so the tokenizer's merges are given many parts at a time, without the pattern. A table that is
full keeps the parts that were met again. Texts with white space before a space are given to the tokenizer whole.
"""

from __future__ import annotations

import os
import re
from itertools import chain

import numpy as np

from . import common

os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")

#: White space beside the space itself.
_WHITE = [chr(c) for c in range(0x3001) if chr(c).isspace() and c != 32]
_JOINT = "\x0b"
#: Latin letters (letters in every version of the character tables) and a mark after them.
_WORD = re.compile("([A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u024f]+)([.,;:!?]?)")
#: Bytes whose kind the pattern goes by (an apostrophe may begin a piece of its own), and parts that the merges get at a time.
_PLAIN = np.zeros(256, bool)
_PLAIN[33:127] = True
_PLAIN[ord("'")] = False
_TOGETHER = 64
_LONGEST = 64  # bytes of a part that is kept
_GROUP = 1 << 20
_HEAD = np.uint64(0x5DEECE66D1234567)
_held: dict = {}
common.held_by_process.append(_held)


def unsafe(text: str) -> bool:
    """Whether white space comes before a space. Most white characters are in no text, which one look each tells."""
    return "  " in text or any([c + " " in text for c in _WHITE if c in text])


def _runs(names: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct names in order, a place of each, and for every name its number."""
    order = np.argsort(names)
    ordered = names[order]
    new = np.ones(len(names), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    number = np.empty(len(names), np.int64)
    number[order] = np.cumsum(new) - 1
    return ordered[new], order[new], number


def plain_bytes(raw: np.ndarray) -> np.ndarray:
    """Which bytes may be in a part that the merges get without the pattern: ASCII but apostrophes, Latin letters, and line
    ends between two other characters (several are cut by what follows them)."""
    ok = _PLAIN[raw]
    after = lambda at: raw[np.minimum(at + 1, len(raw) - 1)]
    at = np.flatnonzero((raw >= 0xC3) & (raw <= 0xC9))
    if len(at):
        first, second = raw[at], after(at)
        sign = (first == 0xC3) & ((second == 0x97) | (second == 0xB7))  # times and divided by
        at = at[~sign & ((first != 0xC9) | (second <= 0x8F))]
        ok[at] = ok[at + 1] = True
    at = np.flatnonzero(raw == 10)
    if len(at):
        before, second = raw[np.maximum(at - 1, 0)], after(at)
        ok[at] = (before != 10) & (before != 32) & (second != 10) & (second != 32)
    return ok


def _tables() -> list[np.ndarray]:
    draw = np.random.default_rng(20240229)
    return [draw.integers(0, 1 << 64, (_LONGEST + 1) * 256, np.uint64, endpoint=False) for _ in range(2)]


class Encoder:
    def __init__(self, path: str, *, specials_as_text: bool = False, cache_size: int = 400_000):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = specials_as_text
        self.cache_size = cache_size
        joint = self._ids(_JOINT)
        self.joint = joint[0] if len(joint) == 1 else None
        self.marks = {c: self._ids(c) for c in ".,;:!?"} | {"": []}
        self.letter = self._byte_letters()
        self.bare = self._without_pattern()
        self.added = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values() if not (specials_as_text and t.special)]
        self.tables = _tables()
        self._begin()

    def _begin(self) -> None:
        """An empty table. names is sorted, slot says where a name's other values are; store holds the ids."""
        self.names, self.slot = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.proof, self.at, self.count = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.store, self.used = np.zeros(1 << 16, np.uint32), 0
        self.again = np.zeros(0, bool)  # per slot: whether its part was met in more than one group since the table was last thinned

    def _thin(self) -> None:
        """Keep the parts that were met again, if they are no more than half the table: most parts of texts are met once."""
        stay = self.again[self.slot]
        if 2 * int(stay.sum()) > self.cache_size:
            self._begin()
            return
        names, slot = self.names[stay], self.slot[stay]
        proof, at, count = self.proof[slot], self.at[slot], self.count[slot]
        end = np.cumsum(count)
        store = self.store[np.repeat(at - (end - count), count) + np.arange(int(count.sum()))]
        self._begin()
        self.names, self.slot, self.proof, self.at, self.count = names, np.arange(len(names)), proof, end - count, count
        self.store, self.used, self.again = np.append(store, self.store), len(store), np.zeros(len(names), bool)

    def _byte_letters(self) -> dict[int, str] | None:
        """How the model writes each byte; None where it doesn't take words written so as they are."""
        from tokenizers import pre_tokenizers

        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        self.letter = {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in set(plain))}
        self.merges, self.space = self.tokenizer.model.tokenize, self.letter[32]
        fits = isinstance(self.tokenizer.pre_tokenizer, pre_tokenizers.ByteLevel) and self.tokenizer.normalizer is None
        return self.letter if fits and all(self._letters(w) == self._ids(" " + w) for w in ("word", "Ünïté", "thandanst")) else None

    def _without_pattern(self):
        """The same merges without the pattern, for parts of ``plain_bytes``; None if a token goes over a cut of the pattern.

        Merges only make tokens of the vocabulary, so where none goes over a cut, the cuts needn't be made."""
        from tokenizers import Tokenizer

        if self.letter is None:
            return None
        latin = "".join(self.letter[b] for b in (*range(0xC3, 0xCA), *range(0x80, 0xC0)))
        kinds = (f"A-Za-z{latin}", "0-9", re.escape("".join(chr(b) for b in range(33, 127) if chr(b) != "'" and not chr(b).isalnum())), self.letter[10])
        whole = re.compile(f"{self.space}?(?:" + "|".join(f"[{k}]+" for k in kinds) + f")|{self.space}+")
        within = re.compile(f"[{self.space}{''.join(kinds)}]+")
        tokens = self.tokenizer.get_vocab(with_added_tokens=False)
        if any(within.fullmatch(t) and not whole.fullmatch(t) for t in tokens):
            return None
        self.led = np.zeros(max(tokens.values()) + 1, bool)  # tokens that begin with a space, hence a part
        self.led[[n for t, n in tokens.items() if t[0] == self.space]] = True
        self.chars = np.array([ord(self.letter[b]) for b in range(256)], "<u4")
        return Tokenizer(self.tokenizer.model)

    def _together(self, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of many parts of plain bytes, each after a space, one after another, and how many each has."""
        written, space = self.chars.take(raw).tobytes().decode("utf-32-le"), np.flatnonzero(raw == 32)
        cuts = [*space[::_TOGETHER].tolist(), len(written)]
        found = self.bare.encode_batch_fast([written[a:b] for a, b in zip(cuts, cuts[1:])], add_special_tokens=False)
        ids = np.concatenate([np.array(x.ids, np.uint32) for x in found])
        begins = np.flatnonzero(self.led[ids])
        if len(begins) != len(space):
            raise RuntimeError("a token goes over the space between two parts")
        return ids, np.diff(begins, append=len(ids))

    def _letters(self, word: str, before: str = " ") -> list[int]:
        written = word if word.isascii() else "".join(map(self.letter.__getitem__, word.encode()))
        return [t.id for t in self.merges(self.space + written if before else written)]

    def _ids(self, text: str) -> list[int]:
        return self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids  # no offsets, the same ids

    def _head(self, part: str) -> list[int]:
        """Ids of a part that begins a text."""
        word = _WORD.fullmatch(part) if self.letter is not None else None
        return self._letters(word[1], "") + self.marks[word[2]] if word else self._ids(part)

    def _learn(self, parts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of parts that a space comes before, one after another, and how many each has."""
        count, flat, plain = np.zeros(len(parts), np.int64), np.zeros(0, np.uint32), np.zeros(len(parts), bool)
        if self.bare is not None and parts:
            data = (" " + " ".join(parts)).encode()
            raw = np.frombuffer(data, np.uint8)
            odd, space = ~plain_bytes(raw), np.flatnonzero(raw == 32)
            for token in self.added:
                odd[[m.start() for m in re.finditer(re.escape(token), data)]] = True
            size = np.diff(space, append=len(raw))
            plain = (size > 1) & (np.add.reduceat(odd, space, dtype=np.int64) == 1)  # the space itself
            if plain.any():
                flat, count[plain] = self._together(raw[np.repeat(plain, size)])
        rest = np.flatnonzero(~plain)
        if not len(rest):
            return flat, count
        ids = self._others([parts[n] for n in rest.tolist()])
        count[rest] = [len(x) for x in ids]
        out, of = np.empty(int(count.sum()), np.uint32), np.repeat(plain, count)
        out[of], out[~of] = flat, np.fromiter(chain.from_iterable(ids), np.uint32)
        return out, count

    def _others(self, parts: list[str]) -> list[list[int]]:
        out: list = [None] * len(parts)
        plain, total = [], 0
        for i, p in enumerate(parts):
            if self.joint is None or not p or p[-1].isspace() or _JOINT in p:
                out[i] = self._ids(" " + p)
            else:
                plain.append(i)
                total += len(p) + 2
                if total > 200_000:
                    self._bulk(parts, plain, out)
                    plain, total = [], 0
        if plain:
            self._bulk(parts, plain, out)
        return out

    def _bulk(self, parts: list[str], which: list[int], out: list) -> None:
        """Encode many parts as one text, joined by a white character that always is a token of its own."""
        ids = self._ids(" " + f"{_JOINT} ".join(parts[i] for i in which))
        cuts = [n for n, x in enumerate(ids) if x == self.joint]
        if len(cuts) != len(which) - 1:
            for i in which:
                out[i] = self._ids(" " + parts[i])
            return
        begin = 0
        for i, end in zip(which, [*cuts, len(ids)]):
            out[i] = ids[begin:end]
            begin = end + 1

    def _put(self, ids: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
        """Ids go to the end of the store: where they begin, and how many they are."""
        count = np.array([len(x) for x in ids], np.int64)
        return self._append(np.fromiter(chain.from_iterable(ids), np.uint32, int(count.sum())), count)

    def _append(self, flat: np.ndarray, count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        end = self.used + np.cumsum(count)
        size = self.used + len(flat)
        if size > len(self.store):
            self.store = np.concatenate((self.store, np.zeros(max(size, 2 * len(self.store)) - len(self.store), np.uint32)))
        self.store[self.used : size] = flat
        self.used = size
        return end - count, count

    def _group(self, segments: list[tuple[bytes, bool]]) -> list[bytes]:
        """Ids of segments (bytes, whether a text begins there; else a space comes before)."""
        if len(self.names) > self.cache_size:
            self._thin()
        data = b" ".join([s for s, _ in segments])
        raw = np.frombuffer(data, np.uint8)
        space = np.flatnonzero(raw == 32)
        starts, ends = np.concatenate(([0], space + 1)), np.append(space, len(raw))
        parts_of = np.array([s.count(b" ") + 1 for s, _ in segments])
        edge = np.concatenate(([0], np.cumsum(parts_of)))
        head = np.zeros(len(starts), bool)
        head[edge[:-1][[h for _, h in segments]]] = True
        size = ends - starts
        place = np.arange(len(raw), dtype=np.int32) - np.repeat(starts.astype(np.int32), size + 1)[: len(raw)]
        np.minimum(place, _LONGEST, out=place)
        place = (place * np.int32(256) + raw).astype(np.intp)  # the kind of number that looks up without another copy
        names = []
        with np.errstate(over="ignore"):
            for table in self.tables:
                sums = np.zeros(len(raw) + 1, np.uint64)
                np.cumsum(table.take(place), dtype=np.uint64, out=sums[1:])
                names.append(sums[ends] - sums[starts] + size.astype(np.uint64) * _HEAD + np.where(head, _HEAD, np.uint64(0)))
        del place, sums
        at, count = np.zeros(len(starts), np.int64), np.zeros(len(starts), np.int64)
        usual = np.flatnonzero(size <= _LONGEST)
        found, first, inverse = _runs(names[0][usual])
        proof = names[1][usual][first]
        where = np.minimum(np.searchsorted(self.names, found), max(len(self.names) - 1, 0))
        known = self.names[where] == found if len(self.names) else np.zeros(len(found), bool)
        slot = np.zeros(len(found), np.int64)
        slot[known] = self.slot[where[known]]
        self.again[slot[known]] = True
        new = np.flatnonzero(~known)
        if len(new):
            i = usual[first[new]]
            words = [data[a:b].decode() for a, b in zip(starts[i].tolist(), ends[i].tolist())]
            begins, put, many = head[i], np.zeros(len(i), np.int64), np.zeros(len(i), np.int64)
            put[~begins], many[~begins] = self._append(*self._learn([words[n] for n in np.flatnonzero(~begins).tolist()]))
            put[begins], many[begins] = self._put([self._head(words[n]) for n in np.flatnonzero(begins).tolist()])
            slot[new] = len(self.proof) + np.arange(len(new))
            self.proof, self.at, self.count = np.append(self.proof, proof[new]), np.append(self.at, put), np.append(self.count, many)
            self.again = np.append(self.again, np.zeros(len(new), bool))
            into = np.searchsorted(self.names, found[new])
            self.names, self.slot = np.insert(self.names, into, found[new]), np.insert(self.slot, into, slot[new])
        if not ((self.proof[slot] == proof).all() and (proof[inverse] == names[1][usual]).all()):
            raise RuntimeError("two parts have the same 64-bit name")
        at[usual], count[usual] = self.at[slot][inverse], self.count[slot][inverse]
        kept, long = self.used, np.flatnonzero(size > _LONGEST)
        if len(long):
            words = [("" if head[n] else " ") + data[starts[n] : ends[n]].decode() for n in long.tolist()]
            at[long], count[long] = self._put([self._ids(w) for w in words])
        stop = np.cumsum(count)
        flat = self.store[np.repeat(at - (stop - count), count) + np.arange(stop[-1])].astype("<u4", copy=False)
        self.used = kept
        cut = np.concatenate(([0], stop))[edge].tolist()
        return [flat[a:b].tobytes() for a, b in zip(cut, cut[1:])]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of every text as little-endian unsigned 32-bit integers."""
        out: list[list[bytes]] = [[] for _ in texts]
        group, owner, total = [], [], 0

        def flush():
            for i, ids in zip(owner, self._group(group)):
                out[i].append(ids)

        for i, t in enumerate(texts):
            if not t:
                continue
            if unsafe(t):
                out[i].append(np.array(self._ids(t), "<u4").tobytes())
                continue
            data, a = t.encode(), 0
            while a <= len(data):  # a long text is cut at spaces
                b = len(data) if len(data) - a <= _GROUP else data.find(b" ", a + _GROUP)
                b = len(data) if b < 0 else b
                group.append((data[a:b], a == 0))
                owner.append(i)
                total += b - a
                a = b + 1
                if total >= _GROUP:
                    flush()
                    group, owner, total = [], [], 0
        if group:
            flush()
        return [b"".join(x) for x in out]


def encoder(path: str, **options) -> Encoder:
    """One encoder per process and setting: Python workers are reused from task to task."""
    key = (path, *sorted(options.items()))
    if key not in _held:
        _held[key] = Encoder(path, **options)
    return _held[key]


def encoder_alone(path: str, **options) -> Encoder:
    """The process's encoder, after all else that it held for other operators has been let go."""
    common.give_back(_held)
    return encoder(path, **options)
