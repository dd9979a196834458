"""SentencePiece encoding and decoding with a unigram lattice (operator 8).

``Vocabulary`` reads a public SentencePiece model file (never trained, never copied
here), keeps every ordinary piece in a double-array trie over UTF-8 bytes, and treats
piece scores as log scores: the encoding is the path of highest total score, the
earlier start winning a tie.  A character that no piece covers becomes its byte pieces
(or the unknown id where the vocabulary has none).

No piece of such a vocabulary holds a white-space marker after another character, so
the lattice falls apart before every run of markers and the best path of a text is the
concatenation of the best paths of those segments.  The property is checked when the
vocabulary is read; a vocabulary without it is encoded text by text.  Segments repeat,
so each task keeps a bounded memo of them and solves the new ones of a batch together,
one numpy step per byte position.

Defined results for odd rows: a null text has null ids, 0 tokens and round_trip null; an
empty text has an empty list; repeated rows are encoded each; an empty table gives an
empty result; a literal U+2581 is read as a space, as the format has it.
"""

from __future__ import annotations

import re
import struct
from collections.abc import Iterator
from itertools import chain
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import share, ship

DEFAULT_MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁".encode()
#: Piece types of the model format, and the penalty of an unknown character: fixed values.
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
UNKNOWN_PENALTY = 10.0
#: Segments that a task remembers, and the longest that the vectorised solver takes.
MEMO = 400_000
WIDE = 64


def _varint(raw: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = raw[at]
        value |= (byte & 127) << shift
        at, shift = at + 1, shift + 7
        if byte < 128:
            return value, at


def _fields(raw: bytes) -> Iterator[tuple[int, object]]:
    """(field number, value) of a protocol-buffer message."""
    at = 0
    while at < len(raw):
        tag, at = _varint(raw, at)
        kind = tag & 7
        if kind == 0:
            value, at = _varint(raw, at)
        elif kind == 2:
            size, at = _varint(raw, at)
            value, at = raw[at : at + size], at + size
        else:
            size = 4 if kind == 5 else 8
            value, at = struct.unpack("<f" if size == 4 else "<d", raw[at : at + size])[0], at + size
        yield tag >> 3, value


def double_array(keys: list[tuple[bytes, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(base, check, value) of a trie: child c of state s is base[s] + c + 1 if check there is s."""
    root: dict = {}
    for key, ident in keys:
        node = root
        for c in key:
            node = node.setdefault(c, {})
        node[-1] = ident
    size = 1 << 16
    base, check, value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
    used = np.zeros(size, bool)
    used[0] = True
    low, hint, todo = 1, {}, [(0, root)]
    while todo:
        state, node = todo.pop()
        value[state] = node.pop(-1, -1)
        codes = np.array(sorted(node), np.int64) + 1
        if not len(codes):
            continue
        kind = min(len(codes), 8)
        start = max(low, hint.get(kind, 0))  # earlier room has failed for nodes this wide
        while True:
            if start + 1024 > len(used):
                more = len(used)
                base, check, value = np.pad(base, (0, more)), np.pad(check, (0, more), constant_values=-1), np.pad(value, (0, more), constant_values=-1)
                used = np.pad(used, (0, more))
            window = np.flatnonzero(~used[start : start + 512]) + start - codes[0]
            window = window[window >= 0]
            fits = window[~used[window[:, None] + codes[None, :]].any(axis=1)] if len(window) else window
            if len(fits):
                break
            start += 512
        hint[kind] = start
        at = int(fits[0])
        base[state] = at
        used[at + codes] = True
        check[at + codes] = state
        while used[low]:
            low += 1
        todo.extend((at + c + 1, child) for c, child in node.items())
    end = int(np.flatnonzero(used)[-1]) + 258
    pad = max(0, end - len(base))
    return tuple(np.pad(x, (0, pad), constant_values=k)[:end] for x, k in ((base, 0), (check, -1), (value, -1)))


class Vocabulary:
    """Pieces, log scores and the trie; small (a few MB), so it is broadcast."""

    def __init__(self, model: bytes) -> None:
        pieces, self.prefix = [], True
        for number, value in _fields(model):
            if number == 1:
                own = dict(_fields(value))
                pieces.append((own.get(1, b""), own.get(2, 0.0), own.get(3, NORMAL)))
            elif number == 3:  # normaliser: whether a marker is put before the text
                self.prefix = bool(dict(_fields(value)).get(3, 1))
        self.size = len(pieces)
        top = max((s for _, s, k in pieces if k == NORMAL), default=0.0)
        least = min((s for _, s, k in pieces if k == NORMAL), default=0.0)
        self.score = np.array([len(p) * top - 0.1 if k == USER else s for p, s, k in pieces])
        self.unknown_score = least - UNKNOWN_PENALTY
        self.unknown = next((i for i, (_, _, k) in enumerate(pieces) if k == UNKNOWN), 0)
        byte = {int(p[3:5], 16): i for i, (p, _, k) in enumerate(pieces) if k == BYTE}
        self.byte = [byte.get(c, -1) for c in range(256)]
        keys = [(p, i) for i, (p, _, k) in enumerate(pieces) if k in (NORMAL, USER) and p]
        self.base, self.check, self.value = double_array(keys)
        self.segments = not any(MARK in re.sub(b"^(?:" + MARK + b")+", b"", p) for p, _ in keys)
        self.surface = [bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else b" \xe2\x81\x87 " if k == UNKNOWN else p.replace(MARK, b" ") for p, _, k in pieces]

    @classmethod
    def read(cls, path: str = DEFAULT_MODEL) -> Vocabulary:
        return cls(Path(path).read_bytes())

    def _emit(self, word: bytes, cuts: list[tuple[int, int, int]]) -> bytes:
        ids: list[int] = []
        for start, end, piece in cuts:
            if piece >= 0:
                ids.append(piece)
            else:
                own = [self.byte[c] for c in word[start:end]]
                ids.extend(own if min(own) >= 0 else [self.unknown])
        return np.array(ids, np.int32).tobytes()

    def solve_one(self, word: bytes) -> bytes:
        """Best path of one marked segment; for those too long for the table below."""
        n = len(word)
        base, check, value, score = self.base, self.check, self.value, self.score
        best, back, piece = [-np.inf] * (n + 1), [0] * (n + 1), [-1] * (n + 1)
        best[0] = 0.0
        for s in range(n):
            here = best[s]
            if here == -np.inf:
                continue
            size, state, single = _width(word[s]), 0, False
            for e in range(s, n):
                nxt = int(base[state]) + word[e] + 1
                if check[nxt] != state:
                    break
                state, ident = nxt, int(value[nxt])
                if ident >= 0:
                    single |= e + 1 - s == size
                    if here + score[ident] > best[e + 1]:
                        best[e + 1], back[e + 1], piece[e + 1] = here + score[ident], s, ident
            e = min(s + size, n)
            if not single and here + self.unknown_score > best[e]:
                best[e], back[e], piece[e] = here + self.unknown_score, s, -1
        cuts, e = [], n
        while e:
            cuts.append((back[e], e, piece[e]))
            e = back[e]
        return self._emit(word, cuts[::-1])

    def solve_many(self, words: list[bytes]) -> list[bytes]:
        """Best paths of short segments, all at once."""
        n, width = len(words), max(map(len, words))
        text = np.zeros((n, width), np.uint8)
        size = np.array([len(w) for w in words])
        text[np.arange(width)[None, :] < size[:, None]] = np.frombuffer(b"".join(words), np.uint8)
        step = WIDTHS[text]
        best = np.full((n, width + 1), -np.inf)
        back, piece = np.zeros((n, width + 1), np.int32), np.full((n, width + 1), -1, np.int32)
        best[:, 0] = 0
        for s in range(width):
            rows = np.flatnonzero((best[:, s] > -np.inf) & (s < size))
            if not len(rows):
                continue
            single = np.zeros(n, bool)
            live, state = rows, np.zeros(len(rows), np.int64)
            for e in range(s, width):
                nxt = self.base[state] + text[live, e].astype(np.int64) + 1
                good = (self.check[nxt] == state) & (e < size[live])
                live, state = live[good], nxt[good]
                if not len(live):
                    break
                ident = self.value[state]
                has = ident >= 0
                r, k = live[has], ident[has]
                single[r[e + 1 - s == step[r, s]]] = True
                total = best[r, s] + self.score[k]
                win = total > best[r, e + 1]
                r = r[win]
                best[r, e + 1], back[r, e + 1], piece[r, e + 1] = total[win], s, k[win]
            r = rows[~single[rows]]
            e = np.minimum(s + step[r, s], size[r])
            total = best[r, s] + self.unknown_score
            win = total > best[r, e]
            best[r[win], e[win]], back[r[win], e[win]], piece[r[win], e[win]] = total[win], s, -1
        out = []
        for word, b, p in zip(words, back.tolist(), piece.tolist(), strict=True):
            cuts, e = [], len(word)
            while e:
                cuts.append((b[e], e, p[e]))
                e = b[e]
            out.append(self._emit(word, cuts[::-1]))
        return out

    def segments_of(self, text: bytes) -> list[bytes]:
        """Keys of a text's segments: the segment without its first space."""
        text = text.replace(MARK, b" ")
        if not text:
            return []
        if not self.prefix or not self.segments:
            return [text]
        if b"  " in text or text[:1] == b" " or text[-1:] == b" ":
            return [s[1:] for s in re.findall(rb" +[^ ]*", b" " + text)]
        return text.split(b" ")

    def encode_many(self, texts: list[bytes], memo: dict[bytes, bytes]) -> list[bytes]:
        """int32 ids of each text as bytes; ``memo`` may be kept between calls."""
        split = [self.segments_of(t) for t in texts]
        if len(memo) > MEMO:
            memo.clear()
        fresh = sorted({s for s in chain.from_iterable(split) if s not in memo}, key=len)
        marked = [((b" " if self.prefix else b"") + s).replace(b" ", MARK) for s in fresh]
        at = 0
        while at < len(fresh):
            if len(marked[at]) > WIDE:
                memo[fresh[at]] = self.solve_one(marked[at])
                at += 1
                continue
            end = at
            while end < len(fresh) and end < at + 20_000 and len(marked[end]) <= min(WIDE, len(marked[at]) + 4):
                end += 1
            memo.update(zip(fresh[at:end], self.solve_many(marked[at:end]), strict=True))
            at = end
        return [b"".join(map(memo.__getitem__, s)) for s in split]

    def decode(self, ids: np.ndarray) -> bytes:
        """The text of a list of ids, without the marker put before it."""
        out = b"".join(map(self.surface.__getitem__, ids.tolist()))
        return out[1:] if self.prefix and out[:1] == b" " else out


def _width(first: int) -> int:
    return 1 if first < 0xC0 else 2 if first < 0xE0 else 3 if first < 0xF0 else 4


WIDTHS = np.array([_width(c) for c in range(256)], np.int64)


def _lists(ids: list[bytes | None]) -> pa.Array:
    offsets = np.cumsum([0] + [len(i or b"") // 4 for i in ids]).astype(np.int64)
    values = pa.array(np.frombuffer(b"".join(i or b"" for i in ids), np.int32))
    made = pa.LargeListArray.from_arrays(pa.array(offsets), values, mask=pa.array([i is None for i in ids])) if len(ids) else pa.array([], pa.large_list(pa.int32()))
    return made.cast(pa.list_(pa.int32()))


def encode(docs: DataFrame, model_path: str = DEFAULT_MODEL, text: str = "text") -> DataFrame:
    """(doc_id, n_tokens, ids, round_trip): every whole text encoded, and decoded again."""
    held = share(docs.sparkSession, Vocabulary.read(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, memo = held(), {}
        for batch in batches:
            at = 0
            every = batch.column(1)
            while at < batch.num_rows:
                part = every.slice(at, 256)
                texts = part.cast(pa.large_binary()).to_pylist()
                ids = vocabulary.encode_many([t or b"" for t in texts], memo)
                same = [None if t is None else vocabulary.decode(np.frombuffer(i, np.int32)) == t.replace(MARK, b" ") for t, i in zip(texts, ids, strict=True)]
                lists = _lists([None if t is None else i for t, i in zip(texts, ids, strict=True)])
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(texts)), pa.array([len(i) // 4 for i in ids], pa.int64()), lists, pa.array(same, pa.bool_())], names=["doc_id", "n_tokens", "ids", "round_trip"])
                at += 256

    return docs.select("doc_id", F.col(text).cast("string").alias("text")).mapInArrow(run, "doc_id long, n_tokens long, ids array<int>, round_trip boolean")


def decode(encoded: DataFrame, model_path: str = DEFAULT_MODEL) -> DataFrame:
    """(doc_id, text) of rows that hold ids; null ids give a null text."""
    held = share(encoded.sparkSession, Vocabulary.read(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [None if i is None else held().decode(np.array(i, np.int32)).decode("utf-8", "replace") for i in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


ship(__name__)
