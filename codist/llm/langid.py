"""Language identification by interpolated Kneser-Ney character models.

One model of five characters for each language, learned from a bounded sample of labelled rows
(``per_language`` rows of each language are expected, dealt by a hash of the row's id; the bound is a
parameter and does not depend on the table). Letters are folded to lower case, and every run of
anything else is one blank. The models of all languages share, for each order, one sorted array of
hashed character sequences with a row of log probabilities, all interpolated, and one for the weights
of contexts. A text gets the language with the least cross-entropy a character; it is accepted when
that lies below a limit for texts of its length. The limits are fitted for a stated rate of false
rejection, ``false_rejection``, on labelled rows that the counts did not use: their first 1, 2, 4, 8 ...
characters are compared with those of other languages and of shuffled texts (``limits``).

Edges: a null text or one without letters is ``und``, with score 0 and not accepted; ties go to the
first language by name; null languages and null texts are not learned from; repeated rows count as
often as they occur; extra columns are passed through, but those named like a result give way to it;
without rows to learn from every text is ``und``.
"""

from __future__ import annotations

import functools
import sys
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass, field
from statistics import NormalDist

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .storage import columns_of, row_and, row_of, ship
from .textarrays import U, chunks, mixed

ORDER = 5
BITS = 12
UNKNOWN, BLANK = 0, 1
POINTS = sys.maxunicode + 1


@functools.cache
def _letters() -> np.ndarray:
    """For each code point its folded letter, or 0 for what is no letter."""
    out = np.zeros(POINTS, dtype=np.uint32)
    for i in range(POINTS):
        c = chr(i)
        if unicodedata.category(c)[0] == "L":
            low = c.lower()
            out[i] = ord(low) if len(low) == 1 else i
    return out


class Alphabet:
    """Symbols of letters: the most frequent of a sample have their own, all others share UNKNOWN."""

    def __init__(self, letters: list[int]):
        self.size = min(len(letters), (1 << BITS) - 2) + 2
        fold = _letters()
        symbol = np.zeros(POINTS, dtype=np.uint16)
        symbol[letters[: self.size - 2]] = np.arange(2, self.size)
        self.table = np.where(fold > 0, symbol[fold], BLANK).astype(np.uint16)

    def read(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of all texts, a blank before each, and where each begins."""
        points = np.frombuffer("\n".join(texts).encode("utf-32-le", "replace"), dtype=np.uint32) if texts else np.zeros(0, np.uint32)
        size = np.fromiter(map(len, texts), dtype=np.int64, count=len(texts))
        begin = np.cumsum(size + 1) - size - 1
        symbols = np.concatenate([[np.uint16(BLANK)], self.table[points]])
        keep = symbols != BLANK
        keep[1:] |= symbols[:-1] != BLANK
        keep[begin] = True
        place = np.cumsum(keep) - 1
        return symbols[keep], np.append(place[begin], place[-1] + 1) if texts else np.zeros(1, np.int64)


def sequences(symbols: np.ndarray, k: int) -> np.ndarray:
    """Code of the k symbols that end at each symbol; symbols before the first count as blanks."""
    out = np.zeros(len(symbols), dtype=U)
    padded = np.concatenate([np.full(k - 1, BLANK, dtype=U), symbols.astype(U)])
    for i in range(k):
        out = (out << U(BITS)) | padded[i : i + len(symbols)]
    return out


def text_sequences(symbols: np.ndarray, first: np.ndarray, k: int) -> np.ndarray:
    """The same within each text: what stands before its beginning counts as blanks."""
    out = sequences(symbols, k)
    for i in range(k - 1):
        at = first[:-1] + i
        at = at[at < first[1:]]
        mask = (U(1) << U(BITS * (i + 1))) - U(1)
        fill = sum(BLANK << (BITS * j) for j in range(i + 1, k))
        out[at] = (out[at] & mask) | U(fill)
    return out


class HashArray:
    """Rows of numbers by hashed key: keys in order, with an index on their top bits."""

    def __init__(self, codes: np.ndarray, rows: np.ndarray):
        keys = mixed(codes)
        order = np.argsort(keys)
        self.keys, self.rows = keys[order], np.ascontiguousarray(rows[order], dtype=np.float32)
        self.shift = U(64 - max(4, int(len(keys)).bit_length() + 1))
        n = 1 << int(U(64) - self.shift)
        self.begin = np.searchsorted(self.keys >> self.shift, np.arange(n + 1, dtype=U)).astype(np.int32)
        self.deepest = int(np.diff(self.begin).max(initial=0))

    def find(self, codes: np.ndarray) -> np.ndarray:
        """Row of each code, or -1."""
        keys = mixed(codes)
        out = np.full(len(keys), -1, dtype=np.int32)
        if not len(self.keys):
            return out
        at = self.begin[(keys >> self.shift).astype(np.int64)]
        last = len(self.keys) - 1
        hit = self.keys[np.minimum(at, last)] == keys
        out[hit] = at[hit]
        todo = np.flatnonzero(~hit)
        for step in range(1, self.deepest):
            if not len(todo):
                break
            place = np.minimum(at[todo] + step, last)
            hit = self.keys[place] == keys[todo]
            out[todo[hit]] = place[hit]
            todo = todo[~hit]
        return out


@dataclass
class Models:
    languages: list[str] = field(default_factory=list)
    alphabet: Alphabet | None = None
    #: For orders 1..ORDER: log2 probabilities, and log2 weights of the contexts of that order.
    grams: list[HashArray] = field(default_factory=list)
    contexts: list[HashArray] = field(default_factory=list)
    #: For each language and class of length (1, 2, 4, 8 ... characters) the most bits a character of accepted texts.
    limit: np.ndarray | None = None

    def _logs(self, symbols: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Log probability of each symbol under each language; 0 for the blank before a text, which is given."""
        code = text_sequences(symbols, first, ORDER)
        row = self.grams[-1].find(code)
        score = self.grams[-1].rows[np.maximum(row, 0)]
        miss = np.flatnonzero(row < 0)
        if len(miss):
            score[miss] = self._backed_off(code[miss], ORDER)
        score[first[:-1]] = 0
        return score

    def bits(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Cross-entropy a character under each language, and the characters and letters of each text."""
        symbols, first = self.alphabet.read(texts)
        if not len(texts):
            return np.zeros((0, len(self.languages))), np.zeros(0, np.int64), np.zeros(0, np.int64)
        total = np.add.reduceat(self._logs(symbols, first), first[:-1], axis=0)
        letters = np.add.reduceat((symbols != BLANK).astype(np.int64), first[:-1])
        size = np.diff(first) - 1
        return -total / np.maximum(size, 1)[:, None], size, letters

    def allowed(self, language: np.ndarray, size: np.ndarray) -> np.ndarray:
        """The most bits a character of accepted texts, between classes of length by the logarithm of the length."""
        place = np.clip(np.log2(np.maximum(size, 1)), 0, self.limit.shape[1] - 1)
        low = np.minimum(place.astype(np.int64), self.limit.shape[1] - 2)
        share = place - low
        return (1 - share) * self.limit[language, low] + share * self.limit[language, low + 1]

    def _backed_off(self, code: np.ndarray, k: int) -> np.ndarray:
        """Of sequences that no language has seen at order k."""
        context = code >> U(BITS)
        at = self.contexts[k - 1].find(context)
        weight = np.where((at >= 0)[:, None], self.contexts[k - 1].rows[np.maximum(at, 0)], np.float32(0))
        code = code & ((U(1) << U(BITS * (k - 1))) - U(1))
        row = self.grams[k - 2].find(code)
        out = self.grams[k - 2].rows[np.maximum(row, 0)]
        miss = np.flatnonzero(row < 0)
        if len(miss):
            out[miss] = self._backed_off(code[miss], k - 1) if k > 2 else self.contexts[0].rows[0] - np.float32(np.log2(self.alphabet.size))
        return weight + out

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray, np.ndarray]:
        """Language, score, cross-entropy, accepted."""
        n = len(texts)
        if not self.languages or not n:
            return ["und"] * n, np.zeros(n), np.full(n, np.inf), np.zeros(n, dtype=bool)
        bits, size, letters = self.bits([x or "" for x in texts])
        best = bits.argmin(axis=1)
        least = bits[np.arange(n), best]
        over = least - self.allowed(best, size)
        share = 1 / np.exp2(np.clip((least[:, None] - bits) * np.minimum(letters, 40)[:, None], -60, 0)).sum(axis=1)
        score = share / (1 + np.exp(np.clip(4 * over, -50, 50)))
        none = letters == 0
        said = ["und" if u else self.languages[b] for u, b in zip(none.tolist(), best.tolist())]
        return said, np.where(none, 0.0, score), least, ~none & (over <= 0)


CLASSES = 14


def _beginnings(logs: np.ndarray, first: np.ndarray, size: int) -> np.ndarray:
    """Cross-entropies a character of the first ``size`` characters of the texts that have so many."""
    total = np.concatenate([[0.0], np.cumsum(logs, dtype=np.float64)])
    begin = first[:-1][np.diff(first) > size] + 1
    return (total[begin] - total[begin + size]) / size


def limits(models: Models, held_out: dict[str, list[str]], false_rejection: float, false_acceptance: float = 0.01) -> np.ndarray:
    """For each language and class of length, the most bits a character of accepted text.

    At the stated rate texts of the language, cut off at that length, need more than ``own`` bits (with fewer
    texts than the rate asks for, at least what the median and the quartiles of a normal law give). Two kinds
    of texts should be rejected: those of other languages, and own texts with their symbols shuffled. Where nearly all of a kind need more than ``own``, any limit between has the same measured
    rates, and the middle of the narrower gap is taken; where a kind overlaps, the limit is ``own``; a kind of
    which most need no more than ``own``, such as a second name of one language, can't be told apart and
    doesn't count. A class without texts
    takes the limit of the class before, a language without held-out texts the bits of evenly drawn symbols.
    """
    out = np.full((len(models.languages), CLASSES), np.log2(models.alphabet.size))
    beyond, rng, held = NormalDist().inv_cdf(1 - false_rejection) / (2 * NormalDist().inv_cdf(0.75)), np.random.default_rng(3), {}
    for name in models.languages:
        if held_out.get(name):
            symbols, first = models.alphabet.read(held_out[name])
            mixed_up, begin = models.alphabet.read(held_out[name][::4])  # enough, as rarer sequences take longer
            for i, j in zip(begin[:-1] + 1, begin[1:]):
                rng.shuffle(mixed_up[i:j])
            held[name] = first, models._logs(symbols, first), begin, models._logs(mixed_up, begin)
    for i, name in enumerate(models.languages):
        for k in range(CLASSES if name in held else 0):
            first, logs, begin, shuffled = held[name]
            mine = _beginnings(logs[:, i], first, 1 << k)
            if not len(mine):
                out[i, k] = out[i, max(k - 1, 0)]
                continue
            low, mid, high, own = np.quantile(mine, [0.25, 0.5, 0.75, 1 - false_rejection])
            if len(mine) * false_rejection < 2:
                own = max(own, mid + beyond * (high - low))
            foreign = [_beginnings(x[:, i], f, 1 << k) for other, (f, x, _, _) in held.items() if other != name]
            kinds = [np.concatenate(foreign) if foreign else mine[:0], _beginnings(shuffled[:, i], begin, 1 << k)]
            bounds = [max(own, np.quantile(x, false_acceptance)) for x in kinds if len(x) and np.median(x) > own]
            out[i, k] = (own + min(bounds)) / 2 if bounds else own
    return out


def fit(samples: dict[str, list[str]], held_out: dict[str, list[str]], false_rejection: float = 0.005) -> Models:
    """Models of the languages of ``samples``; the limits of acceptance come from ``held_out``."""
    languages = sorted(samples)
    if not languages:
        return Models()
    fold = _letters()
    points = np.frombuffer("".join(x for texts in samples.values() for x in texts).encode("utf-32-le", "replace"), dtype=np.uint32)
    counts = np.bincount(fold[points], minlength=POINTS)
    counts[0] = 0
    letters = [i for i in np.argsort(-counts, kind="stable").tolist() if counts[i]]
    alphabet = Alphabet(letters)
    seen = [{} for _ in range(ORDER)]
    for name in languages:
        symbols, first = alphabet.read(samples[name])
        kept = np.ones(len(symbols), dtype=bool)
        kept[first[:-1]] = False
        codes, n = np.unique(text_sequences(symbols, first, ORDER)[kept], return_counts=True)
        for k in range(ORDER, 0, -1):
            seen[k - 1][name] = codes, n
            codes, n = np.unique(codes & ((U(1) << U(BITS * (k - 1))) - U(1)), return_counts=True)  # so many continuations to the left
    models = Models(languages, alphabet)
    below: tuple[np.ndarray, np.ndarray] | None = None
    for k in range(1, ORDER + 1):
        union = np.unique(np.concatenate([seen[k - 1][x][0] for x in languages]))
        contexts = np.unique(union >> U(BITS))
        if below is None:
            lower = np.full((len(union), len(languages)), 1 / alphabet.size)
        else:
            lower = below[1][np.searchsorted(below[0], union & ((U(1) << U(BITS * (k - 1))) - U(1)))]
        prob, weight = np.empty((len(union), len(languages))), np.ones((len(contexts), len(languages)))
        for i, name in enumerate(languages):
            codes, n = seen[k - 1][name]
            once, twice = (n == 1).sum(), (n == 2).sum()
            off = once / (once + 2 * twice) if once else 0.5
            place = np.searchsorted(contexts, codes >> U(BITS))
            total, kinds = np.bincount(place, n, len(contexts)), np.bincount(place, minlength=len(contexts))
            has = total > 0
            weight[has, i] = off * kinds[has] / total[has]
            at = np.searchsorted(contexts, union >> U(BITS))
            prob[:, i] = weight[at, i] * lower[:, i]
            mine = np.searchsorted(union, codes)
            prob[mine, i] += (n - off) / total[place]
        below = union, prob
        models.grams.append(HashArray(union, np.log2(prob)))
        models.contexts.append(HashArray(contexts, np.log2(weight)))
    models.limit = limits(models, held_out, false_rejection)
    return models


def sampled(docs: DataFrame, id_col: str, text_col: str, lang_col: str, per_language: int, most_languages: int = 500) -> tuple[dict, dict]:
    """About ``per_language`` texts of each language to count, and as many others to set limits."""
    rows = docs.select(F.col(id_col).cast("string").alias("id"), F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang")).where("lang is not null and text is not null")
    counts = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().limit(most_languages + 1).collect()}
    if len(counts) > most_languages:
        raise ValueError(f"more than {most_languages} languages")
    if not counts:
        return {}, {}
    share = F.element_at(F.create_map(*[F.lit(x) for k, n in counts.items() for x in (k, min(1.0, 2.0 * per_language / n))]), F.col("lang"))
    picked = rows.where(F.pmod(F.xxhash64("id", F.lit("sample")), F.lit(1 << 20)) < share * (1 << 20))
    learn, calibrate = {}, {}
    for lang, text, side in picked.select("lang", "text", F.pmod(F.xxhash64("id", F.lit("side")), F.lit(2))).toLocalIterator():
        (calibrate if side == 0 else learn).setdefault(lang, []).append(text)
    for lang in calibrate.keys() - learn.keys():
        learn[lang] = calibrate[lang]
    return learn, calibrate


def learn_models(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", per_language: int = 400, false_rejection: float = 0.005) -> Models:
    return fit(*sampled(docs, id_col, text_col, lang_col, per_language), false_rejection)


RESULTS = ("lang_pred", "score", "cross_entropy", "accepted")


def _identified(docs: DataFrame, models: Models, text_col: str) -> DataFrame:
    """(row: the columns of ``docs``, and the results)."""
    held = ship(docs.sparkSession).sparkContext.broadcast(models)
    place = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        models = held.value
        for batch in batches:
            texts = pc.struct_field(batch.column("row"), place).cast(pa.string())
            size = np.nan_to_num(pc.binary_length(texts).to_numpy(zero_copy_only=False)).astype(np.int64)
            for i, j in chunks(np.concatenate([[0], np.cumsum(size)]), 1 << 20):
                said, score, bits, accepted = models.predict(texts.slice(i, j - i).to_pylist())
                yield pa.RecordBatch.from_arrays([batch.column("row").slice(i, j - i), pa.array(said, pa.string()), pa.array(score, pa.float64()), pa.array(bits.astype(np.float64)), pa.array(accepted)], names=["row", *RESULTS])

    return docs.select(row_of(docs).alias("row")).mapInArrow(run, row_and(docs, "lang_pred string, score double, cross_entropy double, accepted boolean"))


def identify(docs: DataFrame, models: Models, text_col: str = "text") -> DataFrame:
    """All columns and lang_pred, score, cross_entropy, accepted; columns that have one of these names give way to it."""
    return _identified(docs, models, text_col).select(*columns_of(docs, but=RESULTS), *RESULTS)


def keep_identified(docs: DataFrame, models: Models, text_col: str = "text", fill: str | None = None) -> DataFrame:
    """The accepted documents, with the columns they had; ``fill`` names a column whose nulls become the language found."""
    held = _identified(docs, models, text_col).where("accepted").select(*columns_of(docs), F.col("lang_pred").alias(found := "".join([*docs.columns, "_found"])))
    return (held if fill is None else held.withColumn(fill, F.coalesce(fill, found))).drop(found)


def fold(id_col: str, of: int) -> Column:
    """crc32 of the id as text, modulo ``of``."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(of))
