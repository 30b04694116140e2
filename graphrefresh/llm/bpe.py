"""Token ids of whole texts from a public tokenizer file, a worker at a time."""

from __future__ import annotations

import os
import re
from array import array
from collections.abc import Iterable
from functools import cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

#: The pattern by which the byte-level tokenizer splits a text before its merges, for the texts below.
PIECES = r"'(?:[stmd]|re|ve|ll)| ?[^\W\d_]+| ?\d+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+"
#: Characters on which Python's classes and the tokenizer's may differ: outside Latin-1, odd separators, superscripts and fractions.
ODD = r"[^\x00-\x1b\x20-\x84\x86-\xb1\xb4-\xb8\xba\xbb\xbf-\xff]"
#: The same for texts of one byte a character: bytes that need no look, and each byte's kind: blank, letter, digit or other.
PLAIN = bytes(i for i in range(256) if not re.match(ODD, chr(i)))
BLANK, LETTER, DIGIT, OTHER, END = range(5)
KINDS = np.array([BLANK if re.match(r"\s", c) else LETTER if re.match(r"[^\W\d_]", c) else DIGIT if re.match(r"\d", c) else OTHER for c in map(chr, range(256))], np.uint8)
#: Pieces remembered by a worker.
REMEMBER = 500_000
#: Bytes of text that are cut together, above which a single text may go.
TOGETHER = 4 << 20
TOKENIZER = "byte_bpe_50k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    if os.path.isabs(name):
        return name
    import public_tokenizers

    return public_tokenizers.path(name)


def pieces(texts: list[bytes]) -> tuple[bytes, np.ndarray, np.ndarray]:
    """The texts (one byte a character, plain ones only) with a byte after each, where their pieces start by ``PIECES``, and which pieces are such bytes."""
    data = b"\0".join([*texts, b""])
    raw, ends = np.frombuffer(data, np.uint8), np.cumsum(np.fromiter(map(len, texts), np.int64, len(texts)) + 1) - 1
    kind = KINDS[raw]
    kind[ends] = END
    start = np.empty(len(raw), bool)
    start[:1] = True
    np.not_equal(kind[1:], kind[:-1], out=start[1:])
    start[ends] = True
    # the last blank before anything else is no part of the run before it, and a space goes with what follows
    last = np.flatnonzero((kind[:-1] == BLANK) & (kind[1:] != BLANK) & (kind[1:] != END))
    start[last] = True
    start[last[raw[last] == 32] + 1] = False
    # an apostrophe that starts a piece takes certain letters with it
    at = np.flatnonzero(raw == 39)
    at = at[start[at]]
    one, two = raw[at + 1], raw[np.minimum(at + 2, len(raw) - 1)]
    short = np.isin(one, np.frombuffer(b"stmd", np.uint8))
    long = ((two == ord("e")) & ((one == ord("r")) | (one == ord("v")))) | ((one == ord("l")) & (two == ord("l")))
    start[at[short | long] + 1] = False
    start[at[short] + 2] = True
    start[at[long] + 3] = True
    starts = np.flatnonzero(start)
    return data, starts, kind[starts] == END


class _Ids:
    """Ids of pieces, looked up many at a time; when too many are kept, only those that came up again stay."""

    def __init__(self, find):
        self.find = find
        self.known, self.ids = pa.array([], pa.binary()), np.array([], "<u4")
        self.first, self.count, self.again = np.array([], np.int64), np.array([], np.int64), np.array([], bool)

    def places(self, strings: pa.BinaryArray) -> np.ndarray:
        """The place of each string in ``first`` and ``count``; new ones are found and added."""
        if len(self.known) > REMEMBER:
            self._keep(np.flatnonzero(self.again))
        at = pc.index_in(strings, value_set=self.known)
        new = strings.filter(at.is_null()) if at.null_count else None
        place = at.fill_null(-1).to_numpy().astype(np.int64)
        self.again[place[place >= 0]] = True
        if new is not None:
            coded = new.dictionary_encode()
            place[place < 0] = len(self.known) + coded.indices.to_numpy()
            self._add(coded.dictionary)
        return place

    def _add(self, strings: pa.BinaryArray) -> None:
        found = self.find(strings.to_pylist())
        count = np.fromiter(map(len, found), np.int64, len(found)) // 4
        self.first = np.concatenate([self.first, len(self.ids) + np.cumsum(count) - count])
        self.known, self.count = pa.concat_arrays([self.known, strings]), np.concatenate([self.count, count])
        self.ids = np.concatenate([self.ids, np.frombuffer(b"".join(found), "<u4")])
        self.again = np.concatenate([self.again, np.zeros(len(found), bool)])

    def _keep(self, kept: np.ndarray) -> None:
        self.ids = self.ids[spread(self.first[kept], self.count[kept])]
        self.known, self.count = self.known.take(pa.array(kept)), self.count[kept]
        self.first, self.again = np.cumsum(self.count) - self.count, np.zeros(len(kept), bool)


def spread(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """``first, first + 1, ..`` of each run of ``count``, one run after the other."""
    upto = np.cumsum(count)
    place = np.repeat(first - (upto - count), count)
    place += np.arange(len(place))
    return place


class Encoder:
    """Encodes texts as little-endian unsigned 32-bit ids.

    A byte-level tokenizer merges inside pieces only, so the ids of a text are those of its pieces. Many texts are cut and
    looked up at a time, by array; different pieces are remembered, new ones are encoded by the tokenizers library, many at a time with line ends between them. A text with a special
    token's string or with an odd character goes to the library whole.
    """

    def __init__(self, name: str = TOKENIZER):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(tokenizer_path(name))
        self.special = [t.content.encode() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.line_end = self.tokenizer.encode("\n", add_special_tokens=False).ids
        self.pieces = _Ids(lambda new: self._new_pieces([p.decode("latin-1") for p in new]))

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]

    def _new_pieces(self, pieces: list[str]) -> list[bytes]:
        if len(self.line_end) != 1:
            return self._whole(pieces)
        out: list[bytes] = [b""] * len(pieces)
        plain = [i for i, p in enumerate(pieces) if not p.isspace()]
        for k in range(0, len(plain), 2000):
            part = plain[k : k + 2000]
            (e,) = self.tokenizer.encode_batch_fast(["\n".join([pieces[i] for i in part])], add_special_tokens=False)
            ids = np.array(e.ids, "<u4")
            ends = [*(4 * np.flatnonzero(ids == self.line_end[0])).tolist(), 4 * len(ids)]
            data, at = ids.tobytes(), 0
            for i, z in zip(part, ends, strict=True):
                out[i] = data[at:z]
                at = z + 4
        blank = [i for i, p in enumerate(pieces) if p.isspace()]
        for i, ids in zip(blank, self._whole([pieces[i] for i in blank]), strict=True):
            out[i] = ids
        return out

    def _by_pieces(self, texts: list[bytes]) -> list[bytes]:
        if not texts:
            return []
        data, starts, ends = pieces(texts)
        bounds = np.append(starts, len(data)).astype("i4")
        place = self.pieces.places(pa.Array.from_buffers(pa.binary(), len(starts), [None, pa.py_buffer(bounds), pa.py_buffer(data)]))
        count = self.pieces.count[place]
        count[ends] = 0
        out, stops = self.pieces.ids[spread(self.pieces.first[place], count)].tobytes(), (4 * np.cumsum(count)[ends]).tolist()
        return [out[a:z] for a, z in zip([0, *stops], stops, strict=False)]

    def _plain(self, text: str) -> bytes | None:
        try:
            b = text.encode("latin-1")
        except UnicodeEncodeError:
            return None
        return None if b.translate(None, PLAIN) or any(s in b for s in self.special) else b

    def encode(self, texts: Iterable[str | None]) -> list[bytes]:
        texts = [t or "" for t in texts]
        out: list[bytes] = [b""] * len(texts)
        plain = list(map(self._plain, texts))
        whole = [i for i, b in enumerate(plain) if b is None]
        at, size = [], 0
        for i, b in enumerate(plain):
            if b is not None:
                at.append(i)
                size += len(b)
            if at and (size > TOGETHER or i == len(plain) - 1):
                for j, ids in zip(at, self._by_pieces([plain[j] for j in at]), strict=True):
                    out[j] = ids
                at, size = [], 0
        for i, ids in zip(whole, self._whole([texts[i] for i in whole]), strict=True):
            out[i] = ids
        return out


@cache
def encoder(name: str = TOKENIZER) -> Encoder:
    """The worker's own encoder, which outlives a task."""
    return Encoder(name)
