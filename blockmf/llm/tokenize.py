"""Fast exact tokenisation with the tokenizers library: pieces of text whose ids do not depend on their surroundings are kept.

A text is cut where no token can cross, the ids of each piece come from the library once and are kept, and the
ids of the text are their concatenation.
* byte-level BPE with the usual pattern: a single space between two non-spaces always starts the next token, so the
  text is cut before such spaces. Texts where a space follows white space go to the library as a whole.
* word BPE (white space dropped, lower case): tokens never hold white space, so the text is cut at it. Texts with the
  control characters about which Python and the library differ in what white space is go to the library as a whole.
Both patterns part a letter from a comma or stop after it, so only what is before it is kept.
Texts that hold one of the vocabulary's added strings (end of text and the like), for which the library has ids of their own, go to it as a whole. The memory for kept pieces is bounded: two generations of
`keep` pieces each, of which the older one goes when the younger one is full.
"""

from __future__ import annotations

import os
import re
from array import array
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_ODD_SPACE = tuple(chr(c) + " " for c in range(0x3001) if chr(c).isspace())
_ODD_CONTROL = tuple("\x1c\x1d\x1e\x1f\x85\u180e\u200b\u2060\ufeff")
_PLAIN = re.compile("[\x00-\u012f\u0131-\u017f]*")  # here Python's lower() is the library's
_STOPS = (",", ".")
#: Byte-level vocabularies write each byte as a visible character: printable Latin-1 as itself, all others from U+0100 on, in order.
_HIDDEN = [b for b in range(256) if not (33 <= b <= 126 or 161 <= b <= 172 or b >= 174)]
_VISIBLE = {b: 256 + i for i, b in enumerate(_HIDDEN)}


class PieceTokenizer:
    def __init__(self, path: str, keep: int | None = None):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are the parallelism
        from tokenizers import Tokenizer

        self.tok = Tokenizer.from_file(path)
        self.added = sorted({t.content for t in self.tok.get_added_tokens_decoder().values() if t.content})
        self.words = self.tok.normalizer is not None  # the word vocabulary normalises and drops white space
        self.dtype = np.dtype("<u2") if self.tok.get_vocab_size() <= 1 << 16 else np.dtype("<u4")
        self.code = {2: "H", 4: "I"}[self.dtype.itemsize]
        self.keep = keep or (200_000 if self.words else 450_000)  # lower case has fewer distinct pieces
        self.lead = "" if self.words else " "
        self.mapped_lead = self.lead.translate(_VISIBLE)
        self.young: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}
        self.starts: dict[str, bytes] = {}
        self.stops = {s: self._ids(s) for s in _STOPS}

    def _ids(self, text: str) -> bytes:
        return np.array(self.tok.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def _learn(self, pieces: set[str]) -> None:
        """Ids of new pieces: from the older generation, from the model alone if a piece is one word for certain, or from the library."""
        if len(self.young) + len(pieces) > self.keep:
            self.old, self.young = self.young, {}
        young, old, model, lead, code, words = self.young, self.old, self.tok.model.tokenize, self.mapped_lead, self.code, self.words
        need = []
        for p in pieces:
            if (got := old.get(p)) is not None:
                young[p] = got
            elif p.isalpha() and (p.isascii() and (not words or p.islower()) or not words or _PLAIN.fullmatch(p) and p == p.lower()):
                q = p if p.isascii() else p.encode().decode("latin-1").translate(_VISIBLE)
                young[p] = array(code, [x.id for x in model(lead + q)]).tobytes()
            else:
                need.append(p)
        for p, e in zip(need, self.tok.encode_batch_fast([self.lead + p for p in need], add_special_tokens=False), strict=True):
            young[p] = array(code, e.ids).tobytes()

    def _first(self, p: str) -> bytes:
        """Ids of a piece that starts a text, so has no space before it."""
        if (got := self.starts.get(p)) is None:
            if len(self.starts) > self.keep // 8:
                self.starts.clear()
            got = array(self.code, [x.id for x in self.tok.model.tokenize(p)]).tobytes() if p.isascii() and p.isalpha() else self._ids(p)
            self.starts[p] = got
        return got

    def _find(self, kinds: list[str]) -> list[bytes]:
        """Ids of distinct pieces. A comma or stop after a letter is a token of its own, so only what is before it is kept."""
        base = [p[:-1] if p.endswith(_STOPS) and p[-2:-1].isalpha() else p for p in kinds]
        found = list(map(self.young.get, base))
        if None in found:
            self._learn({b for b, g in zip(base, found, strict=True) if g is None})
            young = self.young
            found = [young[b] if g is None else g for b, g in zip(base, found, strict=True)]
        return [g + self.stops[p[-1]] if len(p) != len(b) else g for p, b, g in zip(kinds, base, found, strict=True)]

    def _join(self, pieces: list[str]) -> bytes:
        out = []
        for i in range(0, len(pieces), 20_000):  # a very long text must not outgrow what is kept
            kinds = list(dict.fromkeys(part := pieces[i : i + 20_000]))
            out += map(dict(zip(kinds, self._find(kinds), strict=True)).__getitem__, part)
        return b"".join(out)

    def encode(self, text: str) -> bytes:
        """Ids of text as little-endian unsigned integers of self.dtype."""
        if not text:
            return b""
        if any(x in self._lower(text) for x in self.added):
            return self._ids(text)
        if self.words:
            if any(c in text for c in _ODD_CONTROL):
                return self._ids(text)
            return self._join((text.lower() if text.isascii() or _PLAIN.fullmatch(text) else text).split())
        if any(c in text for c in _ODD_SPACE):
            return self._ids(text)
        start, *pieces = text.split(" ")
        return self._first(start) + self._join(pieces)

    def _lower(self, text: str) -> str:
        return text.lower() if self.words else text

    def _added_at(self, data: np.ndarray) -> np.ndarray:
        """Places of added strings in a buffer, also of those that lower case would make."""
        found = [np.zeros(0, np.int64)]
        if self.words:
            data = np.where((data >= 65) & (data <= 90), data + 32, data)
        for raw in (x.encode() for x in self.added):
            at = np.flatnonzero(data[: max(0, len(data) - len(raw) + 1)] == raw[0])
            for k, byte in enumerate(raw[1:], 1):
                at = at[data[at + k] == byte]
            found.append(at)
        return np.concatenate(found)

    def _odd_documents(self, data: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Numbers of documents that encode() would not cut, or whose lower case needs care. A few too many do no harm."""
        if self.words:
            odd = (data >= 0xC6) | ((data >= 28) & (data <= 31))
            pair = (data[:-1] == 0xC2) & (data[1:] == 0x85) | (data[:-1] == 0xC4) & (data[1:] == 0xB0)
            at = np.concatenate([np.flatnonzero(odd), np.flatnonzero(pair)])
        else:
            at = np.flatnonzero(data == 32)
            p1, p2, p3 = (data[np.maximum(at - k, 0)] for k in (1, 2, 3))
            white = (p1 <= 32) & ((p1 >= 28) | (p1 >= 9) & (p1 <= 13)) | (p2 == 0xC2) & ((p1 == 0x85) | (p1 == 0xA0))
            white |= ((p3 == 0xE2) & ((p2 == 0x80) | (p2 == 0x81)) | (p3 == 0xE1) | (p3 == 0xE3)) & (p1 >= 0x80)
            at = at[white & (at > 0)]
        return np.unique(np.searchsorted(ends, np.concatenate([at, self._added_at(data)]), "right"))

    def encode_many(self, texts: pa.Array, end_id: int, size: int = 6 << 20):
        """Yields (token ids, end of each document in them) for runs of documents in order, the end id after each. Same ids as encode():
        the pieces of a run are made and numbered by Arrow, and only distinct ones are looked up."""
        texts = texts.cast(pa.large_string())
        off = np.frombuffer(texts.buffers()[1], np.int64, len(texts) + 1, texts.offset * 8)
        i = 0
        while i < len(texts):
            j = max(i + 1, int(np.searchsorted(off, off[i] + size, "right")) - 1)
            raw = texts.buffers()[2]
            data = np.frombuffer(raw, np.uint8)[off[i] : off[j]] if raw is not None and raw.size else np.zeros(0, np.uint8)
            run, ends = texts.slice(i, j - i), off[i + 1 : j + 1] - off[i]
            odd = self._odd_documents(data, ends) if len(data) else np.zeros(0, np.int64)
            if len(odd) or ends[-1] > 8 * size:
                odd = np.union1d(odd, np.flatnonzero(np.diff(ends, prepend=0) > 8 * size))
                even = np.setdiff1d(np.arange(len(run)), odd)
                parts: list = [None] * len(run)
                if len(even):
                    ids, at = self._encode_run(run.take(pa.array(even)), end_id)
                    for k, x in zip(even, np.split(ids, at[:-1]), strict=True):
                        parts[k] = x
                for k in odd:
                    parts[k] = np.append(np.frombuffer(self.encode(run[int(k)].as_py()), self.dtype), self.dtype.type(end_id))
                yield np.concatenate(parts), np.cumsum([len(x) for x in parts])
            else:
                yield self._encode_run(run, end_id)
            i = j

    def _encode_run(self, run: pa.Array, end_id: int) -> tuple[np.ndarray, np.ndarray]:
        lists = pc.utf8_split_whitespace(pc.utf8_lower(run)) if self.words else pc.split_pattern(run, " ")
        counts = np.diff(np.frombuffer(lists.buffers()[1], np.int64 if pa.types.is_large_list(lists.type) else np.int32, len(run) + 1, lists.offset * (8 if pa.types.is_large_list(lists.type) else 4)))
        numbered = pc.dictionary_encode(lists.flatten())
        numbered = numbered.combine_chunks() if isinstance(numbered, pa.ChunkedArray) else numbered
        kinds = numbered.dictionary.to_pylist()
        found = self._find(kinds)
        which = numbered.indices.to_numpy()
        ends = np.cumsum(counts)
        if not self.words:  # a text's first piece has no space before it
            first = ends - counts
            found += [self._first(kinds[k]) for k in which[first].tolist()]
            which = which.copy()
            which[first] = np.arange(len(run)) + len(kinds)
        found.append(np.array([end_id], self.dtype).tobytes())
        order = np.full(len(which) + len(run), len(found) - 1, np.int64)
        order[np.arange(len(which)) + np.repeat(np.arange(len(run)), counts)] = which
        sizes = np.fromiter(map(len, found), np.int64, len(found)) // self.dtype.itemsize
        values, at = np.frombuffer(b"".join(found), self.dtype), np.cumsum(sizes) - sizes
        n = sizes[order]
        out_end = np.cumsum(n)
        take = np.arange(int(out_end[-1]), dtype=np.int32) + np.repeat((at[order] - (out_end - n)).astype(np.int32), n)  # a run is far below 2^31 ids
        return values[take], out_end[ends + np.arange(len(run))]


@lru_cache(maxsize=4)
def piece_tokenizer(path: str) -> PieceTokenizer:
    return PieceTokenizer(path)


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
