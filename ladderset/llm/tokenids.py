"""Encoding whole texts to token ids, batch by batch, with the tokenizers library.

A vocabulary whose pre-tokenizer drops white space treats the pieces between white space independently,
so each distinct piece of a batch is encoded by the library once and its ids are gathered for every
occurrence; a worker keeps what it has encoded. Any other tokenizer, and any text that holds one of the
vocabulary's special strings, is encoded whole.
"""

from __future__ import annotations

import json
import os
import zlib
from itertools import repeat

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .textscan import LOWER, SPACE, buffer_of

#: Distinct pieces that a worker remembers before it starts afresh (about 150 bytes each).
MEMORY_PIECES = 450_000
#: Bytes of text encoded at a time; a longer single text makes a batch of its own.
SLICE_BYTES = 2 << 20

_LETTER = np.zeros(256, bool)
_LETTER[[*range(65, 91), *range(97, 123)]] = True
_MARK = np.zeros(256, bool)
_MARK[[b for b in range(33, 127) if not (48 <= b <= 57 or _LETTER[b])]] = True


def gather(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """Indices of the concatenated ranges [start, start + length)."""
    total = int(length.sum())
    if not total:
        return np.empty(0, np.int64)
    at = np.cumsum(length) - length
    return np.arange(total) + np.repeat(start - at, length)


def quiet_threads() -> None:
    """One thread in the library's own pool, which is set once a process: a task has a core, and whoever wants more threads starts them."""
    os.environ.setdefault("RAYON_NUM_THREADS", "1")
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "true")


#: The only Replace patterns that can be applied piece by piece: runs of white space.
LOCAL_PATTERNS = {r"\s+", r"\s", " "}


class BatchEncoder:
    """Encodes string columns; `end_id`, if given, closes each text."""

    def __init__(self, path: str, end_id: int | None = None):
        quiet_threads()
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        spec = json.loads(self.tokenizer.to_str())
        self.end_id = end_id
        self.special = [t["content"] for t in spec.get("added_tokens", [])]
        self.by_piece, self.lowers = self._splits_at_space(spec)
        self.closes = None
        if suffix := spec["model"].get("end_of_word_suffix"):
            vocab = self.tokenizer.get_vocab()
            self.closes = np.zeros(max(vocab.values()) + 1, bool)
            self.closes[[i for w, i in vocab.items() if w.endswith(suffix)]] = True
        self._forget()

    @staticmethod
    def _splits_at_space(spec: dict) -> tuple[bool, bool]:
        """Whether white space only separates, so that what lies between can be encoded alone; whether case is dropped."""
        pre, norm = spec.get("pre_tokenizer") or {}, spec.get("normalizer") or {}
        parts = pre.get("pretokenizers", [pre])
        cut = parts[0] if parts else {}
        dropped = cut.get("type") == "Split" and cut.get("behavior") == "Removed" and cut.get("invert") and r"[^\s\p{L}\p{N}]+" in str((cut.get("pattern") or {}).get("Regex"))
        norms = [n for n in norm.get("normalizers", [norm]) if n]
        kinds = [n.get("type") for n in norms]
        replaced = {x for n in norms if n.get("type") == "Replace" for x in (n.get("pattern") or {}).values()}
        local = set(kinds) <= {"NFC", "Replace", "Lowercase"} and replaced <= LOCAL_PATTERNS and not spec.get("truncation") and not spec.get("post_processor")
        return bool(dropped and local), "Lowercase" in kinds

    def _forget(self) -> None:
        self.known: dict[bytes, int] = {}
        self.store, self.at, self.stored, self.count = np.empty(1 << 16, np.uint32), np.zeros(1 << 16, np.int64), 0, 0

    def _learn(self, pieces: list[bytes]) -> None:
        texts = [p.decode("utf-8", "replace") for p in pieces]
        order: list[int] = []
        ids: list[np.ndarray] = []
        length: list[np.ndarray] = []
        if self.closes is not None:
            # words of letters alone give one closing id each, so many can share one call
            alpha = [i for i, t in enumerate(texts) if t.isalpha()]
            packs = [alpha[i : i + 256] for i in range(0, len(alpha), 256)]
            encoded = self.tokenizer.encode_batch_fast([" ".join(texts[i] for i in pack) for pack in packs], add_special_tokens=False)
            for pack, enc in zip(packs, encoded, strict=True):
                flat = np.asarray(enc.ids, np.uint32)
                ends = np.flatnonzero(self.closes[flat]) + 1
                if len(ends) == len(pack) and (not len(ends) or ends[-1] == len(flat)):
                    order += pack
                    ids.append(flat)
                    length.append(np.diff(ends, prepend=0))
        done = set(order)
        rest = [i for i in range(len(texts)) if i not in done]
        for i, enc in zip(rest, self.tokenizer.encode_batch_fast([texts[i] for i in rest], add_special_tokens=False), strict=True):
            order.append(i)
            ids.append(np.asarray(enc.ids, np.uint32))
            length.append(np.array([len(ids[-1])]))
        self._keep([pieces[i] for i in order], ids, length)

    def _keep(self, pieces: list[bytes], ids: list[np.ndarray], length: list[np.ndarray]) -> None:
        """Remembers pieces in this order; their ids may come in any parts, `length` has as many entries as there are pieces."""
        flat = np.concatenate([np.empty(0, np.uint32), *ids])
        ends = self.stored + np.cumsum(np.concatenate([np.empty(0, np.int64), *length]))
        while self.stored + len(flat) > len(self.store):
            self.store = np.concatenate([self.store, np.empty_like(self.store)])
        while self.count + len(pieces) + 1 > len(self.at):
            self.at = np.concatenate([self.at, np.zeros_like(self.at)])
        self.store[self.stored : self.stored + len(flat)] = flat
        self.at[self.count + 1 : self.count + 1 + len(pieces)] = ends
        self.known.update(zip(pieces, range(self.count, self.count + len(pieces)), strict=True))
        self.stored += len(flat)
        self.count += len(pieces)

    def _cut(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Bytes of all pieces, where each starts (and the end), and the index of each row's first piece."""
        space, mark = SPACE[buf], _MARK[buf]
        opens = np.empty(len(buf) + 1, bool)
        opens[0] = True
        opens[1:-1] = space[:-1] | (mark[1:] & _LETTER[buf[:-1]])
        opens[off] = True
        black = ~space
        opens = (opens[:-1] & black)[black]
        kept = buf[black]
        if self.lowers:  # fewer distinct pieces; not before a combining mark, where it could change what composes
            kept = np.where(np.append(kept[1:], 0) < 128, LOWER[kept], kept)
        start = np.append(np.flatnonzero(opens), len(kept)).astype(np.int64)
        seen = np.concatenate([[0], np.cumsum(black, dtype=np.int64)])[off]
        return kept, start, np.searchsorted(start[:-1], seen)

    def _codes(self, kept: np.ndarray, start: np.ndarray) -> np.ndarray:
        """Each piece's place among the remembered ones; new ones are encoded first."""
        pieces = pa.Array.from_buffers(pa.large_binary(), len(start) - 1, [None, pa.py_buffer(start), pa.py_buffer(kept)]).dictionary_encode()
        words = pieces.dictionary.to_pylist()
        if self.count + len(words) > MEMORY_PIECES:
            self._forget()
        place = np.fromiter(map(self.known.get, words, repeat(-1)), np.int64, len(words))
        if len(new := np.flatnonzero(place < 0).tolist()):
            self._learn([words[i] for i in new])
            place[new] = [self.known[words[i]] for i in new]
        return place[pieces.indices.to_numpy(zero_copy_only=False)]

    def _encode_pieces(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        if not len(buf):
            return np.empty(0, np.uint32), np.zeros(len(off), np.int64)
        kept, start, first = self._cut(buf, off)
        code = self._codes(kept, start)
        begin, length = self.at[code], self.at[code + 1] - self.at[code]
        ends = np.concatenate([[0], np.cumsum(length)])
        return self.store[gather(begin, length)], ends[first]

    def _encode_whole(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        texts = [t or "" for t in column.to_pylist()]
        ids = [np.asarray(e.ids, np.uint32) for e in self.tokenizer.encode_batch_fast(texts, add_special_tokens=False)]
        return np.concatenate([*ids, np.empty(0, np.uint32)]), np.concatenate([[0], np.cumsum([len(x) for x in ids])]).astype(np.int64)

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all rows in one array (uint32), and each row's offsets in it. Null is empty."""
        rows = len(column)
        whole = np.zeros(rows, bool)
        if not self.by_piece:
            whole[:] = True
        for s in self.special if self.by_piece else []:
            whole |= pc.fill_null(pc.match_substring(column, s), False).to_numpy(zero_copy_only=False)
        if not whole.any():
            ids, at = self._encode_pieces(*buffer_of(column))
        elif whole.all():
            ids, at = self._encode_whole(column)
        else:
            a, b = np.flatnonzero(~whole), np.flatnonzero(whole)
            (x, xo), (y, yo) = self._encode_pieces(*buffer_of(column.take(pa.array(a)))), self._encode_whole(column.take(pa.array(b)))
            start, length = np.empty(rows, np.int64), np.empty(rows, np.int64)
            start[a], length[a] = xo[:-1], np.diff(xo)
            start[b], length[b] = yo[:-1] + len(x), np.diff(yo)
            ids, at = np.concatenate([x, y])[gather(start, length)], np.concatenate([[0], np.cumsum(length)])
        if self.end_id is not None:
            ids = np.insert(ids, at[1:], self.end_id)
            at = at + np.arange(rows + 1)
        return ids.astype("<u4", copy=False), at

    def batches(self, batch: pa.RecordBatch, text: str = "text"):
        """(row range, ids, offsets) over slices of bounded size."""
        from .textscan import slices

        column = batch.column(batch.schema.get_field_index(text))
        _, off = buffer_of(column)
        for lo, hi in slices(off, SLICE_BYTES):
            ids, at = self.encode(column.slice(lo, hi - lo))
            yield lo, hi, ids, at


_ENCODERS: dict[tuple, BatchEncoder] = {}


def encoder(path: str, end_id: int | None = None) -> BatchEncoder:
    """One encoder a worker process and vocabulary, with what it remembers."""
    if (path, end_id) not in _ENCODERS:
        _ENCODERS[path, end_id] = BatchEncoder(path, end_id)
    return _ENCODERS[path, end_id]


def crc32s(ids: np.ndarray, at: np.ndarray) -> np.ndarray:
    """crc32 of each range of little-endian 32-bit ids."""
    view = memoryview(np.ascontiguousarray(ids, "<u4")).cast("B")
    return np.fromiter((zlib.crc32(view[a * 4 : b * 4]) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)), np.int64, len(at) - 1)


def vocabulary(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)
