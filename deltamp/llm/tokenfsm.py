"""A byte-level BPE tokenizer compiled to finite-state machines.

Two deterministic transducers in a row read a text:

* The splitter reads classes of code points and marks where pieces (words with their leading space,
  runs of digits, marks or white space, contractions) begin. Its transitions carry the marks. A batch
  of texts is cut into chunks of equal length; every chunk yields a map from entry to exit state, the
  maps compose through a parallel prefix scan, and then all chunks run at once from their true entry
  states, however long a single text is.
* The merger reads the bytes of one piece. Its transitions carry the change in the number of tokens
  that the byte brings (below zero when the byte lets earlier tokens merge). Its states are made on
  demand: a state is the longest end of what was read that a token may still continue, with the last
  token and the relative count before each position of that end. A next token is legal after another
  exactly if the two together are tokenised as those two, which decides each transition. Pieces recur, so each
  distinct piece is run once by a worker and its count kept under a 64-bit hash.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex

from . import textbuf
from .grouped import caches, enter

_L, _STMD, _R, _V, _LL, _E, _N, _SP, _WS, _O, _AP, _END = range(12)
_START, _LR, _NR, _OR, _SP1, _SPK, _WS1, _WSK, _APO, _APR, _APV, _APL, _DONE = range(13)
_STATES, _SYMBOLS = 13, 12
#: Code points of a chunk.
CHUNK = 128
#: Distinct pieces that a worker keeps at most before it starts anew.
KEEP = 600_000
#: States of the merger that a worker keeps at most before it starts anew; about 1 kB each.
STATES = 120_000


@lru_cache(maxsize=1)
def _classes() -> np.ndarray:
    """Class of each code point."""
    table = np.full(0x110000, _O, np.uint8)
    every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
    for pattern, kind in ((r"\p{L}", _L), (r"\p{N}", _N), (r"\p{White_Space}", _WS)):
        table[[ord(c) for c in regex.findall(pattern, every)]] = kind
    for chars, kind in (("stmd", _STMD), ("r", _R), ("v", _V), ("l", _LL), ("e", _E), (" ", _SP), ("'", _AP)):
        table[[ord(c) for c in chars]] = kind
    return table


@lru_cache(maxsize=1)
def splitter() -> tuple[np.ndarray, np.ndarray]:
    """Next state and marks by state x symbol: bit 0 a piece begins here, bit 1 it began one place before."""
    here, before = 1, 2
    group = {_L: _LR, _STMD: _LR, _R: _LR, _V: _LR, _LL: _LR, _E: _LR, _N: _NR, _SP: _SP1, _WS: _WS1, _O: _OR, _AP: _APO}
    to = np.zeros((_STATES, _SYMBOLS), np.uint8)
    mark = np.zeros((_STATES, _SYMBOLS), np.uint8)
    for state in range(_STATES):
        for c, fresh in group.items():
            letter, space = fresh == _LR, fresh in (_SP1, _WS1)
            held = _OR if c == _AP else fresh  # after a leading space an apostrophe is an ordinary mark
            longer = _SPK if c == _SP else _WSK
            t, m = fresh, here
            if state == _LR and letter or state == _NR and c == _N or state == _OR and c in (_O, _AP):
                t, m = state, 0
            elif state == _SP1:
                t, m = (longer if space else held), 0
            elif state == _SPK:
                t, m = (longer, 0) if space else (held, before)
            elif state in (_WS1, _WSK):
                t, m = (longer, 0) if space else (fresh, here | before * (state == _WSK))
            elif state == _APO:
                t, m = (_DONE, 0) if c == _STMD else ({_R: _APR, _V: _APV, _LL: _APL}[c], 0) if c in (_R, _V, _LL) else (_OR, 0) if c in (_O, _AP) else (fresh, here)
            elif state in (_APR, _APV, _APL):
                ends = c == (_LL if state == _APL else _E)
                t, m = (_DONE, 0) if ends else (_LR, before) if letter else (fresh, here | before)
            to[state, c], mark[state, c] = t, m
        to[state, _END], mark[state, _END] = _START, before * (state in (_APR, _APV, _APL))
    return to, mark


def scan(symbols: np.ndarray) -> np.ndarray:
    """Marks that the splitter gives at each symbol, begun in its start state."""
    to, mark = (x.ravel() for x in splitter())
    n = -(-max(1, len(symbols)) // CHUNK)
    padded = np.full(n * CHUNK, _END, np.uint8)
    padded[: len(symbols)] = symbols
    columns = np.ascontiguousarray(padded.reshape(n, CHUNK).T)
    maps = np.repeat(np.arange(_STATES, dtype=np.uint8)[:, None], n, 1)
    for j in range(CHUNK):
        maps = to[maps * np.uint8(_SYMBOLS) + columns[j]]
        if j % 8 == 7 and len(maps) > 1 and (maps == maps[0]).all():
            maps = maps[:1]  # one exit state whatever the entry
    maps = np.broadcast_to(maps, (_STATES, n)).copy()
    step = 1
    while step < n:  # inclusive prefix composition: maps[:, k] takes the very first entry to the exit of chunk k
        maps[:, step:] = np.take_along_axis(maps[:, step:], maps[:, :-step], 0)
        step *= 2
    state = np.concatenate(([_START], maps[_START, :-1])).astype(np.uint8)
    out = np.empty((CHUNK, n), np.uint8)
    for j in range(CHUNK):
        code = state * np.uint8(_SYMBOLS) + columns[j]
        out[j] = mark[code]
        state = to[code]
    return np.ascontiguousarray(out.T).ravel()[: len(symbols)]


def pieces(cps: np.ndarray, at: np.ndarray, special: re.Pattern | None, text: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each piece in code points, and the number of pieces before each text."""
    n = len(at) - 1
    size = np.diff(at)
    symbols = np.full(len(cps) + n, _END, np.uint8)
    place = np.arange(len(cps)) + np.repeat(np.arange(n), size)
    symbols[place] = _classes()[cps]
    found = [m.span() for m in special.finditer(text)] if special else []
    if found:
        row = np.searchsorted(at, [a for a, _ in found], "right") - 1
        found = [(a, b) for (a, b), r in zip(found, row, strict=True) if b <= at[r + 1]]
        for a, b in found:
            symbols[place[a:b]] = _END
    marks = scan(symbols)
    begins = (marks & 1).astype(bool)
    begins[:-1] |= (marks[1:] & 2).astype(bool)
    stops = np.flatnonzero(begins | (symbols == _END))
    starts = np.flatnonzero(begins)
    ends = stops[np.searchsorted(stops, starts, "right")]
    shift = np.searchsorted(at[1:] + np.arange(n), starts, "right")  # texts that end before
    starts, ends = starts - shift, ends - shift
    if found:
        a, b = np.array(found).T
        order = np.argsort(np.concatenate((starts, a)), kind="stable")
        starts, ends = np.concatenate((starts, a))[order], np.concatenate((ends, b))[order]
    return starts, ends, np.searchsorted(starts, at)


class Table:
    """Open addressing over numpy arrays: 64-bit hash to a small integer."""

    def __init__(self, bits: int = 16) -> None:
        self.bits, self.n = bits, 0
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.zeros(1 << bits, np.int32)

    def get(self, h: np.ndarray) -> np.ndarray:
        """Value of each hash, -1 if absent."""
        mask = np.int64((1 << self.bits) - 1)
        slot = (h >> np.uint64(64 - self.bits)).astype(np.int64)
        keys = self.keys[slot]
        out = np.where(keys == h, self.values[slot], np.int32(-1))
        left = np.flatnonzero((keys != h) & (keys != 0))
        while len(left):
            slot[left] = (slot[left] + 1) & mask
            keys = self.keys[slot[left]]
            hit = keys == h[left]
            out[left[hit]] = self.values[slot[left[hit]]]
            left = left[~hit & (keys != 0)]
        return out

    def put(self, h: np.ndarray, values: np.ndarray) -> None:
        """Adds distinct hashes that are absent."""
        if 2 * (self.n + len(h)) > len(self.keys):
            old, kept = self.keys[self.keys != 0], self.values[self.keys != 0]
            self.__init__(max(self.bits + 1, int(4 * (self.n + len(h))).bit_length()))
            self.put(old, kept)
        mask = np.int64((1 << self.bits) - 1)
        slot, left = (h >> np.uint64(64 - self.bits)).astype(np.int64), np.arange(len(h))
        while len(left):
            free = left[self.keys[slot[left]] == 0]
            self.keys[slot[free]] = h[free]
            won = free[self.keys[slot[free]] == h[free]]
            self.values[slot[won]] = values[won]
            left = left[self.keys[slot[left]] != h[left]]
            slot[left] = (slot[left] + 1) & mask
        self.n += len(h)


@lru_cache(maxsize=1)
def _code_points() -> np.ndarray:
    return textbuf.letters(0x110000, 99)


def special_pattern(path: str) -> re.Pattern | None:
    """Pattern of the added tokens, which a text may hold verbatim."""
    with open(path, encoding="utf-8") as f:
        added = json.load(f).get("added_tokens", [])
    return re.compile("|".join(re.escape(t["content"]) for t in sorted(added, key=lambda t: -len(t["content"])))) if added else None


class Splitter:
    """Turns string columns into numbers of distinct pieces, which ``resolve`` makes from the new ones' texts."""

    def __init__(self, path: str, resolve: Callable[[list[str]], np.ndarray]) -> None:
        self.special, self.resolve, self.table = special_pattern(path), resolve, Table()

    def lookup(self, raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Value of each piece, and the number of pieces before each text."""
        cps, at = textbuf.codepoints(raw, at)
        text = raw.tobytes().decode("utf-8", "surrogatepass")
        starts, ends, first = pieces(cps, at, self.special, text)
        h = textbuf.span_hashes(_code_points()[cps], starts, ends) | np.uint64(1)
        values = self.table.get(h)
        new = np.flatnonzero(values < 0)
        if len(new):
            distinct, where, inverse = np.unique(h[new], return_index=True, return_inverse=True)
            made = self.resolve([text[a:b] for a, b in zip(starts[new[where]].tolist(), ends[new[where]].tolist(), strict=True)])
            values[new] = made[inverse]
            self.table.put(distinct, made)
        return values, first


def cut_long(raw: np.ndarray, at: np.ndarray, limit: int = textbuf.GROUP_BYTES) -> tuple[np.ndarray, np.ndarray]:
    """Offsets with further cuts in very long texts, always where white space follows other characters, and the row of each part.

    A piece never goes on past such a place, so the parts are split independently.
    """
    cuts, rows = [], []
    for i in np.flatnonzero(np.diff(at) > limit):
        space = np.isin(raw[at[i] : at[i + 1]], (0x20, 0x0A))
        ok = np.flatnonzero(space[1:] & ~space[:-1] & (raw[at[i] : at[i + 1] - 1] < 0x80) & (raw[at[i] : at[i + 1] - 1] > 0x20)) + 1
        k, last = 0, 0
        while (k := int(np.searchsorted(ok, last + limit, "right")) - 1) >= 0 and k < len(ok) and ok[k] > last and at[i + 1] - at[i] - last > limit:
            last = int(ok[k])
            cuts.append(int(at[i]) + last)
            rows.append(int(i))
    every = np.concatenate((at, np.array(cuts, np.int64)))
    row = np.concatenate((np.arange(len(at)), np.array(rows, np.int64)))
    order = np.lexsort((row, every))  # a cut lies inside its text, so it follows the text's own start
    return every[order], row[order]


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in a byte-level vocabulary."""
    plain = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    other = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(other)) for b in range(256)]


class Merger:
    """The lazily made transducer over bytes that counts the tokens of a piece."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        self.added = {t["content"] for t in data.get("added_tokens", [])}
        byte = {c: bytes([b]) for b, c in enumerate(byte_letters())}
        to_bytes = lambda s: b"".join(byte[c] for c in s)
        merges = [m.split(" ") if isinstance(m, str) else m for m in data["model"]["merges"]]
        self.ranks = {(to_bytes(a), to_bytes(b)): i for i, (a, b) in enumerate(merges)}
        self.tokens = {bytes([b]) for b in range(256)} | {a + b for a, b in self.ranks}
        self.prefixes = {t[:k] for t in self.tokens for k in range(1, len(t))}
        self.legal: dict[tuple[bytes, bytes], bool] = {}
        self.ids: dict[tuple, int] = {}
        self.states: list[tuple] = []
        self.moves: dict[int, tuple[int, int]] = {}
        self._state((b"", (b"",), (0,)))

    def _state(self, key: tuple) -> int:
        if key not in self.ids:
            self.ids[key] = len(self.states)
            self.states.append(key)
        return self.ids[key]

    def merge(self, word: bytes) -> list[bytes]:
        """Plain greedy merging of a short string."""
        parts = [word[k : k + 1] for k in range(len(word))]
        while len(parts) > 1:
            best = min(((self.ranks.get(p, 1 << 30), k) for k, p in enumerate(zip(parts, parts[1:], strict=False))), default=(1 << 30, 0))
            if best[0] == 1 << 30:
                break
            parts[best[1] : best[1] + 2] = [parts[best[1]] + parts[best[1] + 1]]
        return parts

    def follows(self, left: bytes, right: bytes) -> bool:
        """Whether ``right`` may come next to ``left`` (empty: nothing)."""
        if (known := self.legal.get((left, right))) is None:
            known = self.legal[left, right] = self.merge(left + right) == ([left, right] if left else [right])
        return known

    def _move(self, state: int, b: int) -> tuple[int, int]:
        end, lasts, counts = self.states[state]
        end += bytes([b])
        for k in range(len(end)):  # a token that begins at place k of the end
            token = end[k:]
            if token in self.tokens and self.follows(lasts[k], token):
                break
        else:
            raise AssertionError("every byte is a token")
        change = counts[k] + 1
        lasts, counts = (*lasts, token), (*counts, change)
        drop = next(k for k in range(len(end) + 1) if k == len(end) or end[k:] in self.prefixes)
        key = (end[drop:], lasts[drop:], tuple(c - change for c in counts[drop:]))
        self.moves[state << 8 | b] = move = (self._state(key), change)
        return move

    def counts(self, words: list[str]) -> np.ndarray:
        """Tokens of each piece; an added token counts as one."""
        out, moves = np.zeros(len(words), np.int32), self.moves
        if len(self.states) > STATES:
            self.ids, self.states, self.legal = {}, [], {}
            moves.clear()
            self._state((b"", (b"",), (0,)))
        for i, w in enumerate(words):
            state = n = 0
            for b in w.encode("utf-8", "surrogatepass"):
                move = moves.get(state << 8 | b) or self._move(state, b)
                state = move[0]
                n += move[1]
            out[i] = 1 if w in self.added else n
        return out


_counters: dict[str, Splitter] = {}
caches("token counts", _counters.clear)


def count(column: pa.Array, path: str) -> np.ndarray:
    """Tokens of each text of a column, 0 for a null."""
    enter("token counts")
    if path not in _counters or _counters[path].table.n > KEEP:
        _counters[path] = Splitter(path, Merger(path).counts)
    whole, at, _ = textbuf.utf8(column)
    out = np.zeros(len(at) - 1, np.int64)
    every, row = cut_long(whole, at)
    for i, j in textbuf.groups(every):
        values, first = _counters[path].lookup(whole[every[i] : every[j]], every[i : j + 1] - every[i])
        sums = np.concatenate(([0], np.cumsum(values, dtype=np.int64)))
        np.add.at(out, row[i:j], sums[first[1:]] - sums[first[:-1]])
    return out
