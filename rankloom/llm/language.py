"""Language identification by multilingual mixture inference.

Learning counts letter trigrams (with word borders) for each language over all
learning documents. A document's words then come from a mixture of languages:
expectation-maximisation estimates the proportions from the words' trigram
likelihoods, and the language set is the one whose likelihood, less a penalty
for each language, is largest. The language with the largest part is predicted.

Edge cases: a null text, or one without a letter, is "und" with score 0 and an
empty set; null languages teach nothing; with nothing to learn from, every text
is "und"; equal texts have equal results.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankloom.llm.words import row_chunks, text_buffers

SLOTS = 1 << 15
BORDER = 1


_LETTERS: dict[str, np.ndarray] = {}


def letters() -> np.ndarray:
    """For each code point: is it a letter?"""
    if not _LETTERS:
        _LETTERS["is"] = np.array([chr(i).isalpha() for i in range(0x110000)])
    return _LETTERS["is"]


class LetterChunk:
    """Trigram slots of some texts: slots, the word of each and the document of each word."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        docs = len(offsets) - 1
        whole = bytes(data[offsets[0] : offsets[-1]])
        heads = data[offsets[0] : offsets[-1]]
        starts_char = (heads & 0xC0) != 0x80
        chars = np.concatenate([[0], np.cumsum(starts_char)])[offsets - offsets[0]]
        points = np.frombuffer(whole.decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
        ascii_up = (points >= 65) & (points <= 90)
        points = np.where(ascii_up, points + 32, points)
        latin_up = (points >= 0xC0) & (points <= 0xDE) & (points != 0xD7)
        points = np.where(latin_up, points + 32, points)
        inside = letters()[np.minimum(points, 0x10FFFF)]
        edge = np.zeros(len(points) + 1, bool)
        edge[chars] = True
        begin = inside.copy()
        begin[1:] &= ~inside[:-1] | edge[1:-1]
        first = np.flatnonzero(begin)
        end = inside.copy()
        end[:-1] &= ~inside[1:] | edge[1:-1]
        last = np.flatnonzero(end)
        code = points.astype(np.uint64)
        before = np.empty_like(code)
        before[1:], before[:1] = code[:-1], BORDER
        after = np.empty_like(code)
        after[:-1], after[-1:] = code[1:], BORDER
        before[first] = BORDER
        after[last] = BORDER
        spots = np.flatnonzero(inside)
        mixed = (before[spots] * np.uint64(0x9E3779B1) + code[spots] * np.uint64(0x85EBCA77C2B2AE63) + after[spots] * np.uint64(0xC2B2AE3D27D4EB4F)) * np.uint64(0x9E3779B97F4A7C15)
        self.slots = (mixed >> np.uint64(49)).astype(np.int64)
        self.word_first = np.searchsorted(spots, first)
        self.doc_first = np.searchsorted(first, chars)
        self.docs = docs


def letter_chunks(column: pa.Array) -> Iterator[tuple[int, int, LetterChunk]]:
    data, offsets = text_buffers(column)
    for lo, hi in row_chunks(offsets, 1 << 20):
        yield lo, hi, LetterChunk(data, offsets[lo : hi + 1])


def may_learn(doc_id: Column) -> Column:
    """crc32 of doc_id as text, mod 4, is not 2."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 != 2


def trigram_counts(docs: DataFrame) -> DataFrame:
    """(lang, slot, n) over all learning documents; each task adds up its own first."""
    rows = docs.filter(may_learn(F.col("doc_id")) & F.col("lang").isNotNull()).select("lang", "text")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}
        for batch in batches:
            coded = batch.column(0).dictionary_encode()
            names, code = coded.dictionary.to_pylist(), coded.indices.to_numpy()
            for lo, hi, chunk in letter_chunks(batch.column(1)):
                per_doc = np.diff(np.append(chunk.word_first, len(chunk.slots))[chunk.doc_first])
                lang = np.repeat(code[lo:hi], per_doc).astype(np.int64)
                flat = np.bincount(lang * SLOTS + chunk.slots, minlength=len(names) * SLOTS).reshape(len(names), SLOTS)
                for name, row in zip(names, flat, strict=True):
                    sums[name] = sums[name] + row if name in sums else row
        for name, row in sums.items():
            slot = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array([name] * len(slot), pa.string()), pa.array(slot.astype(np.int32)), pa.array(row[slot].astype(np.int64))], names=["lang", "slot", "n"])

    counted = rows.mapInArrow(count, "lang string, slot int, n bigint")
    return counted.groupBy("lang", "slot").agg(F.sum("n").alias("n"))


def fitted(docs: DataFrame) -> tuple[list[str], np.ndarray]:
    """(languages, log-likelihood of each slot); the table has SLOTS numbers for each language."""
    table = trigram_counts(docs).toPandas()
    names = sorted(table["lang"].unique())
    counts = np.zeros((len(names), SLOTS))
    counts[np.searchsorted(names, table["lang"]), table["slot"]] = table["n"]
    counts += 0.5
    return names, np.log(counts / counts.sum(1, keepdims=True)).astype(np.float32).T.copy()


def mixture(fit: np.ndarray, owner: np.ndarray, docs: int, allowed: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
    """(proportions, log-likelihood beyond the words' best) for each document.

    fit      word x language likelihoods over the word's best one
    owner    document of each word, ascending
    allowed  document x language
    """
    first = np.searchsorted(owner, np.arange(docs))
    part = allowed / allowed.sum(1, keepdims=True)
    total = np.zeros(docs)
    for k in range(rounds + 1):
        weighted = fit * part[owner]
        whole = weighted.sum(1)
        if k == rounds:
            np.add.at(total, owner, np.log(whole))
            break
        weighted /= whole[:, None]
        sums = np.add.reduceat(weighted, np.minimum(first, len(owner) - 1), axis=0)
        part = sums / sums.sum(1, keepdims=True)
    return part, total


def choose_languages(fit: np.ndarray, log_fit: np.ndarray, owner: np.ndarray, docs: int, rounds: int = 8) -> np.ndarray:
    """Document x language proportions of the language set with the best penalised likelihood.

    fit and owner are of documents with words only. One language is chosen at
    once where no larger set can beat it; else languages go one by one, the
    smallest first, as long as that raises the penalised likelihood.
    """
    langs = fit.shape[1]
    words = np.bincount(owner, minlength=docs)
    first = np.searchsorted(owner, np.arange(docs))
    price = 0.5 * np.log(words + 1.0) + 3.0
    alone = np.add.reduceat(log_fit, first, axis=0)
    single = alone.argmax(1)
    result = np.zeros((docs, langs))
    result[np.arange(docs), single] = 1
    if langs == 1:
        return result
    part, full = mixture(fit, owner, docs, np.ones((docs, langs)), rounds)
    open_docs = np.flatnonzero(alone[np.arange(docs), single] < full - price)
    if not len(open_docs):
        return result
    mine = np.isin(owner, open_docs)
    f, o = fit[mine], np.searchsorted(open_docs, owner[mine])
    allowed = np.ones((len(open_docs), langs))
    now, cost = part[open_docs], price[open_docs]
    best_part, best = now.copy(), full[open_docs] - cost * (langs - 1)
    for size in range(langs - 1, 0, -1):
        smallest = np.where(allowed > 0, now, np.inf).argmin(1)
        allowed[np.arange(len(open_docs)), smallest] = 0
        if size == 1:
            lone = allowed.argmax(1)
            score = alone[open_docs, lone]
            now = allowed.copy()
        else:
            now, score = mixture(f, o, len(open_docs), allowed, rounds)
        score = score - cost * (size - 1)
        better = score >= best
        best_part[better], best[better] = now[better], score[better]
    better = alone[open_docs, single[open_docs]] >= best
    keep = open_docs[~better]
    result[keep] = best_part[~better]
    return result


def identify(docs: DataFrame, names: list[str], table: np.ndarray) -> DataFrame:
    """doc_id, text -> doc_id, lang_pred, score, lang_set over whole texts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            pred, score, sets = ["und"] * n, np.zeros(n), [""] * n
            for lo, _, chunk in letter_chunks(batch.column(1)) if names else ():
                has = np.flatnonzero(np.diff(chunk.doc_first))
                if not len(has):
                    continue
                log_fit = np.add.reduceat(table[chunk.slots], chunk.word_first, axis=0)
                log_fit -= log_fit.max(1, keepdims=True)
                owner = np.repeat(np.arange(len(has)), np.diff(chunk.doc_first)[has])
                part = choose_languages(np.exp(np.maximum(log_fit, -30)), log_fit, owner, len(has))
                for row, p in zip((has + lo).tolist(), part, strict=True):
                    best = int(p.argmax())
                    pred[row], score[row] = names[best], min(1.0, float(p[best]))
                    sets[row] = "+".join(names[i] for i in np.argsort(-p, kind="stable") if p[i] > 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(pred), pa.array(score), pa.array(sets)], names=["doc_id", "lang_pred", "score", "lang_set"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id bigint, lang_pred string, score double, lang_set string")


def predict_languages(docs: DataFrame) -> DataFrame:
    """op7: doc_id, held_out, lang_pred, score, lang_set."""
    names, table = fitted(docs)
    held = F.coalesce(~may_learn(F.col("doc_id")), F.lit(False))
    return identify(docs, names, table).select("doc_id", held.alias("held_out"), "lang_pred", "score", "lang_set")
