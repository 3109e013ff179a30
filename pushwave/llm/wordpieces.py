"""Exact, fast use of a public tokenizer.

The tokenizer drops white space and never joins across it, so a text's ids are those of its
blank-separated chunks in turn. The chunks of many texts are numbered as one Arrow array, so that only
different ones are Python objects; their ids are kept, serialized, in a bounded dictionary.
Where normalizing and splitting a chunk is plain (Latin letters, then perhaps common marks, and
the tokenizer lower-cases, splits letters from marks and maps bytes), its parts are merged by numpy, all
parts of a width together. Every other chunk goes through the whole library.
"""

from __future__ import annotations

import json
import re
from operator import add

import numpy as np
import pyarrow as pa

#: Chunks in one generation of a worker's dictionary; the generation before stays readable.
MOST = 300_000
#: Bytes of text whose chunks are numbered together.
TOGETHER = 4 << 20
#: Marks that may follow a word on the short way; no apostrophe, which the tokenizer joins to letters.
MARKS = ".,!?$%&*#;:)|-"
#: Letters below this go the short way: they have one lower case and no combining marks.
LATIN = "\u0250"
#: Bytes that part chunks.
BLANK = np.zeros(256, bool)
BLANK[list(b" \t\n\r\v\f")] = True

#: A chunk a line: a word of such letters and marks, or else what is none.
_LINE = re.compile(f"^(?:([{''.join(c for c in map(chr, range(ord(LATIN))) if c.isalpha() and c != chr(0x130))}]*)([{re.escape(MARKS)}]*)|(.+))$", re.MULTILINE)


def vocabulary_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _byte_letters() -> dict[int, str]:
    """The public byte-level alphabet: printable Latin-1 stands for itself, the rest follows from 256 on."""
    plain = {b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or b >= 174}
    rest = iter(range(256, 512))
    return {b: chr(b) if b in plain else chr(next(rest)) for b in range(256)}


def _is_plain(path: str) -> bool:
    """Whether the tokenizer is of the kind that the short way renders."""
    with open(path, encoding="utf-8") as f:
        d = json.load(f)
    kinds = [n["type"] for n in (d.get("normalizer") or {}).get("normalizers", [])]
    splits = [p["type"] for p in (d.get("pre_tokenizer") or {}).get("pretokenizers", [])]
    return kinds == ["NFC", "Replace", "Lowercase"] and splits == ["Split", "ByteLevel"] and d["model"]["type"] == "BPE"


class Merges:
    """A byte-pair model's merges over many parts at once. In each part the pair of the least rank, the leftmost
    of equals, is merged until none is left, as the model does it."""

    #: Widest part, in bytes, that is merged here; what stands for no merge.
    WIDE, NONE = 48, np.uint32(0xFFFFFFFF)

    def __init__(self, model: dict, letters: dict[int, str]):
        ids, end = model["vocab"], model.get("end_of_word_suffix") or ""
        self.letter, self.last = (np.array([ids[letters[b] + e] for b in range(256)], np.uint16) for e in ("", end))
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        key = np.array([ids[a] << 16 | ids[b] for a, b in pairs], np.uint32)
        to = np.array([ids[a + b] for a, b in pairs], np.uint32) | np.arange(len(pairs), dtype=np.uint32) << np.uint32(16)
        self.bits = max(8, (4 * len(pairs)).bit_length())
        self.key, self.to = np.zeros(1 << self.bits, np.uint32), np.full(1 << self.bits, self.NONE)  # to: rank, then id
        at = self._slot(key)
        while len(at):  # of those at one free slot the first stays, the others go on to the next
            _, first = np.unique(at, return_index=True)
            stay = np.zeros(len(at), bool)
            stay[first] = self.to[at[first]] == self.NONE
            self.key[at[stay]], self.to[at[stay]] = key[stay], to[stay]
            key, to, at = key[~stay], to[~stay], (at[~stay] + 1) & (len(self.key) - 1)

    @staticmethod
    def of(path: str, letters: dict[int, str]) -> Merges | None:
        """Of a tokenizer's file; None where its model has more to it, is too large or lacks a letter."""
        with open(path, encoding="utf-8") as f:
            m = json.load(f)["model"]
        more = any(m.get(x) for x in ("dropout", "continuing_subword_prefix", "ignore_merges"))
        ends = ("", m.get("end_of_word_suffix") or "")
        if more or max(m["vocab"].values()) >= 1 << 16 or len(m["merges"]) >= 1 << 16 or any(x + e not in m["vocab"] for x in letters.values() for e in ends):
            return None
        return Merges(m, letters)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return (key * np.uint32(0x9E3779B1) >> np.uint32(32 - self.bits)).astype(np.int64)

    def _look(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank and id of each pair's merge, or NONE."""
        key = (a.astype(np.uint32) << np.uint32(16) | b).reshape(-1)
        at = self._slot(key)
        out = self.to[at]
        off = np.flatnonzero((self.key[at] != key) & (out != self.NONE))
        at = at[off]
        while len(off):
            at = (at + 1) & (len(self.key) - 1)
            out[off] = self.to[at]
            on = (self.key[at] != key[off]) & (out[off] != self.NONE)
            off, at = off[on], at[on]
        return out.reshape(a.shape)

    def ids(self, parts: list[bytes]) -> list[bytes]:
        """Packed ids of parts of 1 to WIDE bytes. A merge takes one of a row's ids away, so rows of a width stay together."""
        size = np.fromiter(map(len, parts), np.int64, len(parts))
        order = np.argsort(size, kind="stable")
        border = np.searchsorted(size[order], np.arange(self.WIDE + 2))
        out: list[bytes] = [b""] * len(parts)
        who, ids, rank = np.zeros(0, np.int64), np.zeros((0, self.WIDE), np.uint16), np.zeros((0, self.WIDE - 1), np.uint32)
        for w in range(self.WIDE, 0, -1):
            own = order[border[w] : border[w + 1]]
            if len(own):
                letters = np.frombuffer(b"".join([parts[i] for i in own.tolist()]), np.uint8).reshape(-1, w)
                new = np.concatenate([self.letter[letters[:, :-1]], self.last[letters[:, -1:]]], axis=1)
                who, ids, rank = np.concatenate([who, own]), np.concatenate([ids, new]), np.concatenate([rank, self._look(new[:, :-1], new[:, 1:])])
            go = rank.min(axis=1) != self.NONE if w > 1 else np.zeros(len(who), bool)
            done = ids[~go].tobytes()
            for i, at in zip(who[~go].tolist(), range(0, len(done), 2 * w), strict=True):
                out[i] = done[at : at + 2 * w]
            if w == 1:
                break
            who, ids, rank = who[go], ids[go], rank[go]
            row, j = np.arange(len(who)), rank.argmin(axis=1)
            ids[row, j] = rank[row, j] & np.uint32(0xFFFF)
            stay = np.ones(ids.shape, bool)
            stay[row, j + 1] = False
            ids = ids[stay].reshape(len(who), w - 1)
            stay = np.ones(rank.shape, bool)
            stay[row, j] = False
            rank = rank[stay].reshape(len(who), w - 2)
            for has, a in ((j > 0, -1), (j < w - 2, 0)):  # the pairs that the new id is in
                r, at = row[has], j[has] + a
                rank[r, at] = self._look(ids[r, at], ids[r, at + 1])
        return out


class ChunkCodec:
    """Texts to id bytes: little-endian unsigned of 2 bytes if the vocabulary allows, else 4."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        self.plain = _is_plain(path)
        self.letters = _byte_letters()
        self.dtype = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 65536 else "<u4")
        self.merges = Merges.of(path, self.letters) if self.plain else None
        self.known: dict[bytes, bytes] = {}
        self.before: dict[bytes, bytes] = {}

    def _merge(self, part: bytes) -> bytes:
        """Ids of one run of letters or of marks, by the library's model alone."""
        return np.array([t.id for t in self.model.tokenize("".join(map(self.letters.__getitem__, part)))], self.dtype).tobytes()

    def _parts(self, parts: list[str]) -> dict[str, bytes]:
        """Ids of runs of letters or of marks."""
        coded = "\n".join(parts).encode().split(b"\n")
        if self.merges is None:
            return dict(zip(parts, map(self._merge, coded), strict=True))
        short = [p if len(p) <= Merges.WIDE else b"" for p in coded]
        return dict(zip(parts, [ids or (self._merge(p) if p else b"") for ids, p in zip(self.merges.ids(short), coded, strict=True)], strict=True))

    def learn(self, new: list[bytes]) -> None:
        """Ids of different chunks, many at once: what can be said of all their letters together is not said chunk by chunk."""
        known, ask = self.known, new
        if self.plain:
            # Chunks hold no white space, so each is a line; a line that isn't plain is the third group.
            words, marks, others = zip(*_LINE.findall(b"\n".join(new).decode("utf-8", "replace")), strict=True)
            low = "\n".join(words).lower().split("\n")
            parts = self._parts(list({*low, *marks}))
            known.update(zip(new, map(add, map(parts.__getitem__, low), map(parts.__getitem__, marks)), strict=True))
            ask = [c for c, other in zip(new, others, strict=True) if other]
        if ask:
            texts = [c.decode("utf-8", "replace") for c in ask]
            for c, e in zip(ask, self.tokenizer.encode_batch(texts, add_special_tokens=False), strict=True):
                known[c] = np.asarray(e.ids, self.dtype).tobytes()

    def _ids(self, chunks: list[bytes]) -> list[bytes]:
        """Ids of different chunks."""
        if len(self.known) > MOST:
            self.known, self.before = {}, self.known
        known = self.known
        found = list(map(known.get, chunks))
        lacks = [c for c, x in zip(chunks, found, strict=True) if x is None]
        if not lacks:
            return found
        old = list(map(self.before.get, lacks))
        known.update([(c, x) for c, x in zip(lacks, old, strict=True) if x is not None])
        if new := [c for c, x in zip(lacks, old, strict=True) if x is None]:
            self.learn(new)
        return list(map(known.__getitem__, chunks))

    def forget(self) -> None:
        """Let all chunks go: a worker would hold them beside the memory of whatever it does next."""
        self.known, self.before = {}, {}

    def encode(self, texts: list[bytes | None]) -> list[bytes]:
        out, s = [], 0
        while s < len(texts):
            e, total = s, 0
            while e < len(texts) and (e == s or total < TOGETHER):
                total += len(texts[e] or b"")
                e += 1
            out += self._together(texts[s:e])
            s = e
        return out

    def _together(self, texts: list[bytes | None]) -> list[bytes]:
        data = np.frombuffer(b" ".join([b"", *(t or b"" for t in texts), b""]), np.uint8)
        begin = np.cumsum([1, *(len(t or b"") + 1 for t in texts)])  # of each text, and past the last
        held = ~BLANK[data]
        border = np.flatnonzero(held[1:] != held[:-1]) + 1  # begins and ends of chunks in turn
        first, size = border[::2], border[1::2] - border[::2]
        place = np.append(0, np.cumsum(size)).astype(np.int32)
        chunks = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(place), pa.py_buffer(data[held])]).dictionary_encode()
        ids = pa.array(self._ids(chunks.dictionary.to_pylist()), pa.large_binary()).take(chunks.indices)
        if not len(ids):
            return [b""] * len(texts)
        _, offsets, packed = ids.buffers()
        at = np.frombuffer(offsets, np.int64)[ids.offset : ids.offset + len(ids) + 1][np.searchsorted(first, begin)].tolist()
        whole = memoryview(packed) if packed is not None else b""
        return [bytes(whole[a:b]) for a, b in zip(at, at[1:], strict=False)]


_CODECS: dict[str, ChunkCodec] = {}


def codec(path: str) -> ChunkCodec:
    """One codec a worker, kept between its tasks."""
    if path not in _CODECS:
        _CODECS[path] = ChunkCodec(path)
    return _CODECS[path]
