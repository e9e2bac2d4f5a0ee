"""Whole-text token ids by a tokenizers-library vocabulary, looked up by white-space chunk.

The vocabulary's pre-tokenizer never joins characters across white space, so the ids of a text are the ids of its chunks
one after another; a chunk goes to the library once per worker. Texts are cut into chunks, hashed and looked up as
arrays: a table of 64-bit hashes gives each chunk its ids' place in one long row. A text that holds a special token's
string, or one of the four control characters that Python alone counts as white space, goes to the library whole.
"""

from __future__ import annotations

import json
import os
import re
from collections.abc import Iterator
from itertools import islice

import numpy as np

from pipeflow.llm.common import mixed, resident

#: A word of Latin-1 letters in lower case, the ASCII signs but for the apostrophe behind it, and the rest.
PARTS = re.compile(r"^([a-zß-öø-ÿ]*)([!-&(-/:-@\[-`{-~]*)(.*)$", re.M).findall
#: Byte-level vocabularies write bytes without a printable character as code points from 256 on; those that letters need.
SHIFTED = {chr(b): chr(256 + 33 + b - 127) for b in range(127, 161)} | {chr(173): chr(256 + 67)}
ODD = ("<|", "\x1c", "\x1d", "\x1e", "\x1f")
BLANK = np.isin(np.arange(256), list(b" \t\n\x0b\x0c\r"))
#: Bytes that are looked up at a time, or one text more; longer texts are taken apart at white space.
STRETCH = 1 << 19
BASE = 0x9E3779B97F4A7C15


class Chunks:
    """Ids of chunks by the chunk's hash. Open addressing in arrays, at most half full."""

    def __init__(self, room: int):
        self.room = room
        self.bits = max(10, (2 * room).bit_length())
        self._clear()

    def _clear(self) -> None:
        self.keys, self.slot = np.zeros(1 << self.bits, np.uint64), np.zeros(1 << self.bits, np.int32)
        self.hashes, self.first, self.count = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.flat, self.used = np.zeros(1 << 12, np.uint32), 0

    def find(self, h: np.ndarray) -> np.ndarray:
        """Entry of each hash, -1 where there is none."""
        out, at, todo = np.full(len(h), -1, np.int32), (h >> np.uint64(64 - self.bits)).astype(np.int64), np.arange(len(h))
        while len(todo):
            k = self.keys[at[todo]]
            hit = k == h[todo]
            out[todo[hit]] = self.slot[at[todo[hit]]]
            todo = todo[~hit & (k != 0)]
            at[todo] = (at[todo] + 1) & (len(self.keys) - 1)
        return out

    def add(self, h: np.ndarray, ids: list[bytes]) -> None:
        """h: hashes that aren't there yet, all different."""
        row, sizes = np.frombuffer(b"".join(ids), "<u4"), np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        if self.used + len(row) > len(self.flat):
            self.flat = np.concatenate([self.flat[: self.used], np.zeros(self.used + 2 * len(row), np.uint32)])
        self.flat[self.used : self.used + len(row)] = row
        entry = np.arange(len(self.hashes), len(self.hashes) + len(h)).astype(np.int32)
        self.hashes, self.first, self.count = np.concatenate([self.hashes, h]), np.concatenate([self.first, self.used + np.cumsum(sizes) - sizes]), np.concatenate([self.count, sizes])
        self.used += len(row)
        while 2 * len(self.hashes) > len(self.keys):  # one call may bring more than the room
            self.bits += 1
            self.keys, self.slot = np.zeros(1 << self.bits, np.uint64), np.zeros(1 << self.bits, np.int32)
            h, entry = self.hashes, np.arange(len(self.hashes)).astype(np.int32)
        self._place(h, entry)

    def _place(self, h: np.ndarray, entry: np.ndarray) -> None:
        at = (h >> np.uint64(64 - self.bits)).astype(np.int64)
        todo = np.arange(len(h))
        while len(todo):
            free = todo[self.keys[at[todo]] == 0]
            places, i = np.unique(at[free], return_index=True)
            won = free[i]
            self.keys[places], self.slot[places] = h[won], entry[won]
            lost = np.ones(len(h), bool)
            lost[won] = False
            todo = todo[lost[todo]]
            at[todo] = (at[todo] + 1) & (len(self.keys) - 1)

    def trim(self) -> None:
        """Beyond the room the later half goes: the first entries are the frequent ones."""
        if len(self.hashes) <= self.room:
            return
        h, ids = self.hashes[: self.room // 2], [self.flat[a : a + n].tobytes() for a, n in zip(self.first[: self.room // 2].tolist(), self.count.tolist(), strict=False)]
        self.bits = max(10, (2 * self.room).bit_length())
        self._clear()
        self.add(h, ids)


class Encoder:
    """ids(texts) -> packed little-endian unsigned 32-bit ids of each text. Holds at most `room` chunks."""

    def __init__(self, path: str, room: int = 600_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            plain = json.load(f)
        # for words that are normalised already: the same model behind a split at blanks
        plain |= {"normalizer": None, "pre_tokenizer": {"type": "WhitespaceSplit"}, "added_tokens": []}
        self.lean = Tokenizer.from_str(json.dumps(plain))
        vocab = self.tokenizer.get_vocab(with_added_tokens=True)
        self.ends = np.zeros(max(vocab.values()) + 1, bool)
        self.ends[[i for token, i in vocab.items() if token.endswith("</w>")]] = True
        self.room, self.chunks, self.cores = room, Chunks(room), {}
        self.tails: dict[str, bytes] = {"": b""}
        self._powers(STRETCH)

    def _powers(self, n: int) -> None:
        """Powers of the hash's base and of its inverse modulo 2^64."""
        self.up, self.down = (np.concatenate([np.ones(1, np.uint64), np.multiply.accumulate(np.full(n, x, np.uint64))]) for x in (BASE, pow(BASE, -1, 1 << 64)))

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [np.array(x.ids, "<u4").tobytes() for x in self.tokenizer.encode_batch(texts, add_special_tokens=False)]

    def _learn_cores(self, cores: list[str]) -> None:
        """cores: lower-case words of Latin-1 letters. One token of each ends the word, so the ids can be told apart."""
        joined = " ".join(cores).encode().decode("latin-1")
        if not joined.isascii():
            for a, b in SHIFTED.items():
                joined = joined.replace(a, b)
        ids = np.array(self.lean.encode_batch_fast([joined], add_special_tokens=False)[0].ids, "<u4")
        stops = (np.flatnonzero(self.ends[ids]) + 1) * 4
        if len(stops) != len(cores):
            self.cores.update(zip(cores, self._whole(cores), strict=True))
            return
        raw, stops = ids.tobytes(), stops.tolist()
        self.cores.update(zip(cores, map(raw.__getitem__, map(slice, [0, *stops], stops)), strict=False))

    def _learn(self, chunks: list[str]) -> list[bytes]:
        """The ids of chunks. A chunk is a word and what follows it, two pre-tokens; the word's ids don't depend on its case."""
        known, tails = self.cores, self.tails
        # no chunk holds a line end, so all are lowered and taken apart in one go
        parts = PARTS("\n".join(chunks).lower())
        if len(parts) != len(chunks):
            return self._whole(chunks)
        new = {core for core, _, more in parts if core and not more}.difference(known)
        if new:
            self._learn_cores(list(new))
        signs = list({tail for core, tail, more in parts if core and not more}.difference(tails))
        tails.update(zip(signs, self._whole(signs), strict=True))
        rest = iter(self._whole([chunk for chunk, (core, _, more) in zip(chunks, parts, strict=True) if not core or more]))
        return [next(rest) if not core or more else known[core] + tails[tail] for core, tail, more in parts]

    def _trim(self) -> None:
        self.chunks.trim()
        if len(self.tails) > 1000:
            self.tails = {"": b""}
        if len(self.cores) > self.room // 4:
            self.cores = dict(islice(self.cores.items(), self.room // 8))

    def _look_up(self, texts: list[bytes]) -> list[bytes]:
        joined = b"\n".join(texts)
        b = np.frombuffer(joined, np.uint8)
        if len(b) >= len(self.up):
            self._powers(len(b))
        stops = np.flatnonzero(np.diff(BLANK[b].view(np.int8), prepend=1, append=1))
        first, last = stops[::2], stops[1::2]
        # the sum of a chunk's bytes times powers of the base, brought to a common power
        sums = np.zeros(len(b) + 1, np.uint64)
        np.cumsum((b.astype(np.uint64) + np.uint64(1)) * self.up[: len(b)], out=sums[1:])
        h = mixed((sums[last] - sums[first]) * self.down[first]) | np.uint64(1)
        entry = self.chunks.find(h)
        lost = np.flatnonzero(entry < 0)
        if len(lost):
            new, at = np.unique(h[lost], return_index=True)
            pick = lost[at]
            names = "\n".join(joined[a:z].decode() for a, z in zip(first[pick].tolist(), last[pick].tolist(), strict=True)).split("\n")
            self.chunks.add(new, self._learn(names))
            entry[lost] = self.chunks.find(h[lost])
        count = self.chunks.count[entry]
        ends = np.cumsum(count)
        ids = self.chunks.flat[np.repeat(self.chunks.first[entry] - (ends - count), count) + np.arange(ends[-1] if len(ends) else 0)]
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        begins = np.concatenate([[0], ends])[np.searchsorted(first, np.cumsum(sizes + 1) - sizes - 1)].tolist()
        raw = ids.astype("<u4").tobytes()
        return [raw[4 * a : 4 * z] for a, z in zip(begins, [*begins[1:], len(ids)], strict=True)]

    def ids(self, texts: list[str]) -> list[bytes]:
        out: list[list[bytes]] = [[] for _ in texts]
        odd, held, owner, size = [], [], [], 0

        def work() -> None:
            for i, x in zip(owner, self._look_up(held), strict=True):
                out[i].append(x)
            self._trim()

        for i, text in enumerate(texts):
            if any(x in text for x in ODD):
                odd.append(i)
                continue
            for raw in stretches(text.encode()):
                held.append(raw)
                owner.append(i)
                size += len(raw)
                if size >= STRETCH:
                    work()
                    held, owner, size = [], [], 0
        if held:
            work()
        for i, x in zip(odd, self._whole([texts[i] for i in odd]), strict=True):
            out[i].append(x)
        return [x[0] if len(x) == 1 else b"".join(x) for x in out]


def stretches(raw: bytes) -> Iterator[bytes]:
    """raw in stretches that end at white space."""
    if len(raw) <= 2 * STRETCH:
        yield raw
        return
    at, gap = 0, re.compile(rb"[ \t\n\x0b\x0c\r]")
    while at < len(raw):
        found = gap.search(raw, at + STRETCH)
        stop = found.end() if found else len(raw)
        yield raw[at:stop]
        at = stop


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def encoder(path: str) -> Encoder:
    """One encoder per worker process, until the worker turns to other work."""
    return resident(("encoder", path), lambda: Encoder(path))
