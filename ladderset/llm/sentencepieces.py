"""SentencePiece encoding and decoding on the tokenizers library.

The model file is read field by field (it is a protocol buffer). From it a tokenizers pipeline is rebuilt:
the normaliser (compiled character map, white-space rules, the metaspace mark), a unigram model with its
scores or a BPE model whose merges follow from the pieces' scores, byte fallback, and the decoder.

Where no piece of the vocabulary holds a mark after another character, a piece can't reach over the start
of a run of spaces, so runs of spaces with what follows them are encoded on their own: each distinct one of a batch
goes through the library once, many at a time, on several threads. Every one of them is compared with the
sentencepiece library when it is first seen, so each document carries a verdict on parity that covers all its text. Where they
differ (pieces that tie to the last bit can come out in another order) the library's own ids are taken.

Defined cases: null text is empty and has no ids; rows that repeat are encoded one by one; a text that
holds the mark itself is encoded whole; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

import struct
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import table
from .textscan import buffer_of, per_row_sum, slices
from .tokenids import BatchEncoder, crc32s, gather, quiet_threads, vocabulary

MARK = "▁"
NORMAL, UNKNOWN, CONTROL, USER, BYTE = 1, 2, 3, 4, 6
UNIGRAM, BPE = 1, 2
SLICE_BYTES = 3 << 20
THREADS = 2
#: Pieces encoded in one call.
TOGETHER = 128


def fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(field number, value) of a protocol-buffer message; 32-bit and 64-bit values stay bytes."""
    at = 0

    def varint() -> int:
        nonlocal at
        value = shift = 0
        while True:
            b = data[at]
            at += 1
            value |= (b & 127) << shift
            shift += 7
            if b < 128:
                return value

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        else:
            size = {1: 8, 5: 4}.get(kind) or varint()
            yield tag >> 3, data[at : at + size]
            at += size


@dataclass
class PieceModel:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    charsmap: bytes = b""
    dummy_prefix: bool = True
    trims: bool = True
    escapes: bool = True
    unk_surface: str = " ⁇ "

    @staticmethod
    def parse(data: bytes) -> PieceModel:
        m = PieceModel()
        for n, v in fields(data):
            if n == 1:
                text, score, kind = "", 0.0, NORMAL
                for k, x in fields(v):
                    text, score, kind = (x.decode(), score, kind) if k == 1 else (text, struct.unpack("<f", x)[0], kind) if k == 2 else (text, score, x) if k == 3 else (text, score, kind)
                m.pieces.append((text, score, kind))
            elif n == 2:
                got = dict(fields(v))
                m.kind, m.byte_fallback = got.get(3, UNIGRAM), bool(got.get(35, 0))
                m.unk_surface = got[44].decode() if 44 in got else m.unk_surface
            elif n == 3:
                got = dict(fields(v))
                m.charsmap, m.dummy_prefix, m.trims, m.escapes = got.get(2, b""), bool(got.get(3, 1)), bool(got.get(4, 1)), bool(got.get(5, 1))
        return m

    @property
    def unk(self) -> int:
        return next((i for i, (_, _, k) in enumerate(self.pieces) if k == UNKNOWN), 0)

    def merges(self) -> list[tuple[str, str]]:
        """All ways to join two pieces into a third; better third pieces first."""
        place = {p: i for i, (p, _, k) in enumerate(self.pieces) if k in (NORMAL, USER)}
        out = []
        for p, i in place.items():
            out += [(-self.pieces[i][1], i, place[p[:c]], place[p[c:]], p[:c], p[c:]) for c in range(1, len(p)) if p[:c] in place and p[c:] in place]
        return [(a, b) for *_, a, b in sorted(out)]

    def separable(self) -> bool:
        """Whether no piece reaches over the start of a run of spaces, and spaces are kept as they are. Unigram models add up scores over a
        whole text in single precision, so where two ways are nearly equal, what comes before decides: their texts stay whole."""
        inner = any(MARK in p.lstrip(MARK) for p, _, k in self.pieces if k in (NORMAL, USER))
        return self.kind == BPE and not (inner or self.charsmap or self.trims) and self.escapes and self.dummy_prefix and not any(k == USER for *_, k in self.pieces)

    def tokenizer(self, whole: bool = True):
        """The tokenizers pipeline; with whole=False for a run of spaces and what follows, without the dummy prefix."""
        from tokenizers import Regex, Tokenizer, decoders, models, normalizers

        if self.kind == BPE:
            vocab = {p: i for i, (p, _, _) in enumerate(self.pieces)}
            model = models.BPE(vocab, self.merges(), unk_token=self.pieces[self.unk][0], fuse_unk=True, byte_fallback=self.byte_fallback)
        elif self.kind == UNIGRAM:
            model = models.Unigram([(p, s) for p, s, _ in self.pieces], self.unk, self.byte_fallback)
        else:
            raise ValueError("only unigram and BPE models")
        out = Tokenizer(model)
        steps = [normalizers.Precompiled(self.charsmap)] if self.charsmap else []
        if self.trims:
            steps += [normalizers.Replace(Regex(" {2,}"), " "), normalizers.Strip()]
        if self.dummy_prefix and whole:
            steps.append(normalizers.Prepend(MARK))
        if self.escapes:
            steps.append(normalizers.Replace(" ", MARK))
        out.normalizer = normalizers.Sequence(steps)
        back = [decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse()]
        out.decoder = decoders.Sequence(back + ([decoders.Strip(" ", 1, 0)] if self.dummy_prefix else []))
        return out

    def surface(self) -> list[bytes]:
        """What each id stands for in decoded bytes."""
        out = []
        for p, _, k in self.pieces:
            out.append(bytes([int(p[3:5], 16)]) if k == BYTE else b"" if k == CONTROL else self.unk_surface.encode() if k == UNKNOWN else p.replace(MARK, " ").encode())
        return out


class PieceEncoder(BatchEncoder):
    """Encodes and decodes string columns with a SentencePiece model."""

    def __init__(self, path: str, threads: int = THREADS):
        quiet_threads()
        import sentencepiece

        self.threads = threads

        with open(path, "rb") as f:
            self.model = PieceModel.parse(f.read())
        self.reference = sentencepiece.SentencePieceProcessor(model_file=path)
        self.end_id, self.special, self.by_piece = None, [MARK], self.model.separable()
        self.tokenizer, self.inner = self.model.tokenizer(), self.model.tokenizer(whole=False)
        surface = self.model.surface()
        self.surface, self.surface_at = np.frombuffer(b"".join(surface), np.uint8), np.concatenate([[0], np.cumsum([len(s) for s in surface])])
        self._forget()

    def _forget(self) -> None:
        super()._forget()
        self.same = np.zeros(0, bool)

    def _encoded(self, texts: list[str]) -> list:
        """The library lets other threads run while it encodes, so a batch is dealt to as many of ours, whatever its own pool is set to."""
        part = -(-len(texts) // self.threads)
        if part < TOGETHER:
            return self.inner.encode_batch_fast(texts, add_special_tokens=False)
        with ThreadPoolExecutor(self.threads) as pool:
            done = pool.map(lambda lo: self.inner.encode_batch_fast(texts[lo : lo + part], add_special_tokens=False), range(0, len(texts), part))
            return [enc for batch in done for enc in batch]

    def _learn(self, pieces: list[bytes]) -> None:
        texts = [p.decode("utf-8", "replace") for p in pieces]
        ids: list[np.ndarray | None] = [None] * len(texts)
        same = np.ones(len(texts), bool)
        # pieces that end in no space can share a call: nothing reaches from one into the next
        firm = [i for i, t in enumerate(texts) if t[-1] != " "]
        packs = [firm[i : i + TOGETHER] for i in range(0, len(firm), TOGETHER)]
        joined = ["".join(texts[i] for i in pack) for pack in packs]
        theirs = self.reference.encode([j[1:] for j in joined], num_threads=1)  # the library adds the first space by itself
        for pack, enc, ref in zip(packs, self._encoded(joined), theirs, strict=True):
            flat = np.asarray(enc.ids, np.uint32)
            reach = np.cumsum(np.diff(self.surface_at)[flat])
            want = np.cumsum([len(pieces[i]) for i in pack])
            ends = np.searchsorted(reach, want) + 1
            if ends[-1] == len(flat) and (reach[ends - 1] == want).all() and flat.tolist() == ref:
                for i, a, b in zip(pack, [0, *ends[:-1].tolist()], ends.tolist(), strict=True):
                    ids[i] = flat[a:b]
        rest = [i for i, x in enumerate(ids) if x is None]
        for i, enc in zip(rest, self._encoded([texts[i] for i in rest]), strict=True):
            want = enc.ids if texts[i] == " " else self.reference.encode(texts[i][1:])
            ids[i], same[i] = np.asarray(want, np.uint32), want == enc.ids
        self.same = np.concatenate([self.same, same])
        self._keep(pieces, ids, [np.array([len(x) for x in ids], np.int64)])

    def _cut(self, buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        some = np.flatnonzero(np.diff(off) > 0)
        full = np.insert(buf, off[some], 32)
        grown = off + np.concatenate([[0], np.cumsum(np.diff(off) > 0)])
        space = full == 32
        opens = space.copy()
        opens[1:] &= ~space[:-1]
        opens[grown[:-1][some]] = True
        start = np.append(np.flatnonzero(opens), len(full)).astype(np.int64)
        return full, start, np.searchsorted(start[:-1], grown)

    def encode_checked(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The sentencepiece library's ids, offsets, and whether the rebuilt pipeline gave them by itself."""
        import pyarrow.compute as pc

        rows = len(column)
        odd = pc.fill_null(pc.match_substring(column, MARK), False).to_numpy(zero_copy_only=False) if self.by_piece else np.ones(rows, bool)
        if odd.any():
            ids, at = self.encode(column)
            wanted = [np.asarray(self.reference.encode(t.as_py() or ""), np.uint32) for t in column]
            parity = np.array([np.array_equal(w, ids[a:b]) for w, a, b in zip(wanted, at[:-1], at[1:], strict=True)], bool)
            if not parity.all():
                ids, at = np.concatenate([np.empty(0, np.uint32), *wanted]), np.concatenate([[0], np.cumsum([len(w) for w in wanted])])
            return ids, at, parity
        buf, off = buffer_of(column)
        if not len(buf):
            return np.empty(0, np.uint32), np.zeros(rows + 1, np.int64), np.ones(rows, bool)
        kept, start, first = self._cut(buf, off)
        code = self._codes(kept, start)
        begin, length = self.at[code], self.at[code + 1] - self.at[code]
        ends = np.concatenate([[0], np.cumsum(length)])
        return self.store[gather(begin, length)], ends[first], per_row_sum(~self.same[code], first) == 0

    def decode(self, ids: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Decoded bytes and row offsets."""
        begin, length = self.surface_at[ids], np.diff(self.surface_at)[ids]
        raw = self.surface[gather(begin, length)]
        ends = np.concatenate([[0], np.cumsum(length)])[at]
        if self.model.dummy_prefix:  # the prefix goes from each row that has it
            lead = ends[:-1][(ends[1:] > ends[:-1])]
            lead = lead[raw[lead] == 32]
            cut = np.searchsorted(lead, ends)
            raw, ends = np.delete(raw, lead), ends - cut
        return raw, ends


_OPEN: dict[tuple, PieceEncoder] = {}


def piece_encoder(path: str, threads: int = THREADS) -> PieceEncoder:
    if (path, threads) not in _OPEN:
        _OPEN[path, threads] = PieceEncoder(path, threads)
    return _OPEN[path, threads]


def encode_pieces(docs: DataFrame, model: str, id_col: str = "doc_id", text_col: str = "text", threads: int = THREADS, with_ids: bool = False) -> DataFrame:
    """doc_id, n_tokens, ids_crc32, parity (same ids as sentencepiece), round_trip (decoding gives the text), and ids if asked for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = piece_encoder(model, threads)
        for batch in batches:
            _, whole = buffer_of(batch.column(1))
            for lo, hi in slices(whole, SLICE_BYTES):
                text = batch.column(1).slice(lo, hi - lo)
                ids, at, parity = enc.encode_checked(text)
                raw, ends = enc.decode(ids, at)
                buf, off = buffer_of(text)
                same = np.diff(off) == np.diff(ends)
                if len(buf) == len(raw) and same.all():
                    same = per_row_sum(buf != raw, off) == 0
                else:
                    same = np.array([s and buf[a:b].tobytes() == raw[c:d].tobytes() for s, a, b, c, d in zip(same, off[:-1], off[1:], ends[:-1], ends[1:], strict=True)], bool)
                cols = [batch.column(0).slice(lo, hi - lo), pa.array(np.diff(at)), pa.array(crc32s(ids, at)), pa.array(parity), pa.array(same)]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(at, pa.int32()), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(cols, names)

    schema = "doc_id long, n_tokens long, ids_crc32 long, parity boolean, round_trip boolean" + (", ids array<int>" if with_ids else "")
    names = [x.split()[0] for x in schema.split(", ")]
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, schema)


def decode_pieces(encoded: DataFrame, model: str) -> DataFrame:
    """doc_id and text from doc_id and ids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = piece_encoder(model)
        for batch in batches:
            ids = batch.column(1).fill_null([])
            at = ids.offsets.to_numpy().astype(np.int64)
            raw, ends = enc.decode(ids.values.to_numpy()[at[0] : at[-1]], at - at[0])
            text = [raw[a:b].tobytes().decode("utf-8", "replace") for a, b in zip(ends[:-1], ends[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(text, pa.string())], ["doc_id", "text"])

    return encoded.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def op7_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_pieces(table(spark, sf_dir, "documents"), vocabulary("piece_bpe_32k.model"))
