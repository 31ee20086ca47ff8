"""Quality rules as a short-circuit cascade.

Each rule rejects on a few statistics of the text. On a bounded sample every rule is timed and its
rejection rate measured; rules then run in the order of rejections per unit of cost, each on the
documents that no earlier rule has rejected: their bytes, words and lines are copied out before the next
rule computes anything. The verdict is the same in any order, so the sample only decides the speed.
Statistics are computed with numpy over whole Arrow batches and shared by rules.

Words are `[^\\x20\\x09-\\x0D]+`. The default rules are meant to spare clean prose in any language: too
few words, repeated 5-word windows, symbols like markup residue, lines that repeat, words of absurd
length, and shouting (nearly all letters upper case with many exclamation marks).

Defined cases: null or empty text has no words (and is rejected by the first rule); rows that repeat are
judged one by one, whatever their ids; an empty table gives an empty result; all columns of the input are
carried, but `kept`, and with digest=True the names of the base statistics, replace columns of those names.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .support import plainly_named, quoted, table
from .textscan import SPACE, Words, buffer_of, mix, per_row_sum, range_hash, slices, window_hash, words_of

SLICE_BYTES = 2 << 20
#: The sample that orders the rules: so many whole texts of at most so many bytes, one in so many by hash.
SAMPLE_ROWS = 400
SAMPLE_TEXT_BYTES = 1 << 16
SAMPLE_SHARE = 8

_SYMBOL = np.zeros(256, bool)
_SYMBOL[[ord(c) for c in "#*$%&|<>"]] = True
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_LOWERCASE = np.zeros(256, bool)
_LOWERCASE[97:123] = True


class TextStats:
    """Statistics of a slice of texts, each computed when first asked for."""

    def __init__(self, buf: np.ndarray, off: np.ndarray):
        self.buf, self.off, self.rows = buf, off, len(off) - 1
        self._got: dict[str, np.ndarray] = {}

    def __getattr__(self, name: str):
        if name.startswith("_") or (make := getattr(type(self), f"_{name}", None)) is None:
            raise AttributeError(name)
        if name not in self._got:
            self._got[name] = make(self)
        return self._got[name]

    def take(self, rows: np.ndarray) -> TextStats:
        """Copies of some rows (ascending), with what is known of them already."""
        if len(rows) == self.rows:
            return self
        length = np.diff(self.off)
        stays = np.zeros(self.rows, bool)
        stays[rows] = True
        off = np.concatenate([[0], np.cumsum(length[rows])])
        out = TextStats(self.buf[np.repeat(stays, length)], off)
        out._got = {k: v[rows] for k, v in self._got.items() if isinstance(v, np.ndarray)}
        new = np.cumsum(stays) - 1

        def moved(start: np.ndarray, end: np.ndarray, row: np.ndarray) -> tuple[np.ndarray, ...]:
            mine = stays[row]
            to = new[row[mine]]
            back = self.off[row[mine]] - off[to]
            return start[mine] - back, end[mine] - back, to

        if (w := self._got.get("words")) is not None:
            start, end, row = moved(w.start, w.end, w.row)
            out._got["words"] = Words(start, end, row, np.concatenate([[0], np.cumsum(np.diff(w.first)[rows])]))
        if (got := self._got.get("lines")) is not None:
            out._got["lines"] = moved(*got)
        return out

    def _words(self):
        return words_of(self.buf, self.off)

    def _n_words(self):
        return np.diff(self.words.first)

    def _word_chars(self):
        return per_row_sum(~SPACE[self.buf] & ((self.buf & 0xC0) != 0x80), self.off)

    def _n_symbols(self):
        return per_row_sum(_SYMBOL[self.buf], self.off)

    def _n_upper(self):
        return per_row_sum(_UPPER[self.buf], self.off)

    def _n_lower(self):
        return per_row_sum(_LOWERCASE[self.buf], self.off)

    def _n_shouts(self):
        return per_row_sum(self.buf == ord("!"), self.off)

    def _lines(self):
        """(start, end, row) of the lines that hold a word."""
        cut = np.flatnonzero(self.buf == 10)
        start = np.unique(np.concatenate([self.off[:-1][np.diff(self.off) > 0], cut + 1]))
        start = start[start < len(self.buf)]
        row = np.searchsorted(self.off, start, "right") - 1
        ends = np.unique(np.concatenate([cut, self.off[1:]]))
        end = np.where(self.buf[start] == 10, start, ends[np.searchsorted(ends, start, "right")])
        some = np.searchsorted(self.words.start, start) < np.searchsorted(self.words.start, end)
        return start[some], end[some], row[some]

    def _n_lines(self):
        return np.bincount(self.lines[2], minlength=self.rows)

    def _n_dup_lines(self):
        start, end, row = self.lines
        key = mix(range_hash(self.buf, start, end) + mix(row.astype(np.uint64) + np.uint64(1)))
        order = np.argsort(key)
        again = np.zeros(len(order), bool)
        again[1:] = key[order[1:]] == key[order[:-1]]
        return np.bincount(row[order[again]], minlength=self.rows)

    def _n_repeat_words(self):
        w = self.words
        h, at = window_hash(range_hash(self.buf, w.start, w.end), w.row, 5)
        if not len(h):
            return np.zeros(self.rows, np.int64)
        h = mix(h + mix(w.row[at].astype(np.uint64) + np.uint64(1)))
        order = np.argsort(h)
        s = h[order]
        same = np.zeros(len(s) + 1, bool)
        same[1:-1] = s[1:] == s[:-1]
        hit = at[order[same[1:] | same[:-1]]]
        cover = np.zeros(len(w.start) + 1, np.int64)
        np.add.at(cover, hit, 1)
        np.add.at(cover, hit + 5, -1)
        total = np.concatenate([[0], np.cumsum(np.cumsum(cover[:-1]) > 0)])
        return total[w.first[1:]] - total[w.first[:-1]]


@dataclass(frozen=True)
class Rule:
    name: str
    rejects: Callable[[TextStats], np.ndarray]


BASE_RULES = [
    Rule("too_few_words", lambda s: s.n_words < 10),
    Rule("repeated_windows", lambda s: 100 * s.n_repeat_words > 20 * s.n_words),
]
EXTRA_RULES = [
    Rule("symbols", lambda s: s.n_symbols > s.n_words),
    Rule("repeated_lines", lambda s: 10 * s.n_dup_lines > 5 * s.n_lines),
    Rule("word_length", lambda s: (s.word_chars < 2 * s.n_words) | (s.word_chars > 40 * s.n_words)),
    Rule("shouting", lambda s: (s.n_upper > 4 * s.n_lower) & (10 * s.n_shouts > 3 * s.n_words)),
]
RULES = BASE_RULES + EXTRA_RULES


def order_rules(sample: list[str | None], rules: list[Rule]) -> list[tuple[Rule, float, float]]:
    """Rules by rejections per second on the sample, with cost (seconds a row) and selectivity."""
    buf, off = buffer_of(pa.array(sample, pa.string()))
    rows, out = max(1, len(sample)), []
    for rule in rules:
        stats, began = TextStats(buf, off), time.perf_counter()
        hit = int(np.count_nonzero(rule.rejects(stats)))
        out.append((rule, (time.perf_counter() - began) / rows, hit / rows))
    return sorted(out, key=lambda x: (-x[2] / max(x[1], 1e-12), x[1]))


def cascade(stats: TextStats, rules: list[Rule]) -> np.ndarray:
    """Rows that no rule rejects; each rule sees only what earlier ones left."""
    alive = np.arange(stats.rows)
    for rule in rules:
        if not len(alive):
            break
        stays = np.flatnonzero(~rule.rejects(stats))
        alive, stats = alive[stays], stats.take(stays)
    return alive


BASE_STATISTICS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
DIGEST = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean"


def apply_rules(docs: DataFrame, text_col: str = "text", rules: list[Rule] | None = None, sample_rows: int = SAMPLE_ROWS, digest: bool = False) -> DataFrame:
    """All columns of `docs` and `kept`; with digest=True the base statistics as well (computed for every row)."""
    spark_rules = RULES if rules is None else rules
    added = ["kept", *([*BASE_STATISTICS, "base_failed"] if digest else [])]
    text = docs.select(F.col(quoted(text_col)).cast("string").alias("t"))
    drawn = text.where((F.pmod(F.xxhash64("t"), F.lit(SAMPLE_SHARE)) == 0) & (F.coalesce(F.octet_length("t"), F.lit(0)) <= SAMPLE_TEXT_BYTES))
    ordered = [r for r, _, _ in order_rules([r["t"] for r in drawn.limit(sample_rows).collect()], spark_rules)]
    names = [n for n in docs.columns if n not in added]
    place = names.index(text_col)
    picked = [spark_rules.index(r) for r in ordered]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rules_here = [(RULES if rules is None else rules)[i] for i in picked]
        for batch in batches:
            buf, off = buffer_of(batch.column(place))
            for lo, hi in slices(off, SLICE_BYTES):
                stats = TextStats(buf[off[lo] : off[hi]], off[lo : hi + 1] - off[lo])
                if digest:
                    base = BASE_RULES[0].rejects(stats) | BASE_RULES[1].rejects(stats)
                    told = [pa.array(np.asarray(getattr(stats, n), np.int64)) for n in BASE_STATISTICS] + [pa.array(base)]
                kept = np.zeros(hi - lo, bool)
                kept[cascade(stats, rules_here)] = True
                cols = [*batch.slice(lo, hi - lo).columns, pa.array(kept), *(told if digest else [])]
                yield pa.RecordBatch.from_arrays(cols, [*names, *added])

    carried, kinds = plainly_named(docs, names)
    schema = ", ".join(f"{quoted(n)} {kind}" for n, kind in zip(names, kinds, strict=True)) + ", kept boolean"
    return carried.mapInArrow(run, schema + (f", {DIGEST}" if digest else ""))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = apply_rules(table(spark, sf_dir, "documents").select("doc_id", "text"), digest=True)
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


_WORD, _SPLIT = r"[^\x20\x09-\x0D]+", "string_split(t, chr(10))"
ORACLE = {
    "op10_quality_rules": rf"""
        WITH w AS (SELECT doc_id, coalesce(text, '') AS t, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS ws FROM documents),
        line AS (SELECT doc_id, count(*) AS lines, count(*) - count(DISTINCT x) AS dups FROM (SELECT doc_id, unnest({_SPLIT}) AS x FROM w) WHERE regexp_matches(x, '{_WORD}') GROUP BY 1),
        win AS (SELECT doc_id, i, array_to_string(ws[i:i + 4], ' ') AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 3)) AS i FROM w WHERE len(ws) >= 5)),
        twice AS (SELECT doc_id, g FROM win GROUP BY 1, 2 HAVING count(*) > 1),
        covered AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM win JOIN twice USING (doc_id, g), (SELECT unnest(range(5)) AS j) GROUP BY 1),
        stat AS (SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(coalesce(list_sum(list_transform(ws, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
            CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, CAST(coalesce(dups, 0) AS BIGINT) AS n_dup_lines, CAST(coalesce(covered.n, 0) AS BIGINT) AS n_repeat_words,
            coalesce(lines, 0) AS n_lines, length(regexp_replace(t, '[^A-Z]', '', 'g')) AS up, length(regexp_replace(t, '[^a-z]', '', 'g')) AS low, length(regexp_replace(t, '[^!]', '', 'g')) AS shouts
            FROM w LEFT JOIN line USING (doc_id) LEFT JOIN covered USING (doc_id)),
        base AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM stat)
        SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
            NOT (base_failed OR n_symbols > n_words OR 10 * n_dup_lines > 5 * n_lines OR word_chars < 2 * n_words OR word_chars > 40 * n_words OR (up > 4 * low AND 10 * shouts > 3 * n_words)) AS kept
        FROM base
    """
}
