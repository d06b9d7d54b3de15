"""Benchmark decontamination over a BM25 index of the test items.

The items are indexed, not the corpus: BM25 weights, divided by an item's score
against itself, in postings by blocks of items with a largest weight for each
term and block. Every passage of a training text (a window of two strides, a
stride holding the longest item) is a query. As in block-max WAND a pivot parts its
terms: those of little weight, which together stay below a share of the threshold,
are skipped, and the postings of the others drive. A block is looked at where their
largest weights in it and the skipped terms' could reach the threshold, and opened
where the block's largest weights of all terms do. All items at or above the threshold are retrieved and then verified:
word five-grams of the question part and of the answer part must recur. A part of
fewer than fifteen words, of which one edit would break most five-grams, may recur
by runs of a third of its words instead, but only close to the other part.

The index travels to the executors. It is built for SLICE items at most; a larger
benchmark is served in slices, each with a pass of its own. Document frequencies,
mean and largest length are those of the whole benchmark for every slice, so that
slices do not change a score.

Items of fewer than min_words words are matched exactly, as a whole word sequence.

Edge cases: a null text or item is empty and an item without words matches
nothing; an item with a null id is searched like any other; equal items match alike; an empty
benchmark matches nothing; a text shorter than a window is one passage.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankloom.llm.common import written
from rankloom.llm.words import WordChunk, forget_powers, mix64, tidy, word_chunks

SLICE, BLOCK_ITEMS = 20_000, 4
#: What is worked on together: terms of passages, postings of blocks, opened blocks.
TERMS_AT_ONCE, POSTINGS_AT_ONCE, OPEN_AT_ONCE = 1 << 18, 1 << 21, 1 << 12
#: The share of the threshold that the skipped terms may reach (any share gives the same result), and room for rounding.
SKIPPED, ROUNDING = 0.5, 1e-9
K1, B = 1.2, 0.75
GRAM, SHARE = 5, 3


def hashed_words(text: str) -> np.ndarray:
    data = np.frombuffer(text.encode(), np.uint8)
    return WordChunk(data, np.array([0, len(data)]), True).hashes


def grams(words: np.ndarray, width: int) -> np.ndarray:
    """Codes of runs of width words."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    code = words[:n].copy()
    for k in range(1, width):
        code = mix64(code * np.uint64(0x9E3779B97F4A7C15) + words[k : n + k])
    return code


def question_and_answer(text: str) -> tuple[str, str]:
    """An item's two parts: up to its last question mark, or all sentences but the last, or halves."""
    if "?" in text.rstrip(" ?\n"):
        cut = text.rstrip(" ?\n").rindex("?") + 1
        return text[:cut], text[cut:]
    sentences = re.split(r"(?<=[.!?])\s+", text.strip())
    if len(sentences) > 1:
        return " ".join(sentences[:-1]), sentences[-1]
    words = text.split()
    return " ".join(words[: -(-len(words) // 2)]), " ".join(words[-(-len(words) // 2) :])


def spread(first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(number of the range, element) for all elements of ranges first, first + 1, ... of given sizes."""
    which = np.repeat(np.arange(len(first)), size)
    return which, np.arange(len(which)) + (first - np.concatenate([[0], np.cumsum(size)[:-1]]))[which] if len(first) else which


def distinct(codes: np.ndarray) -> np.ndarray:
    """Different codes in order, by sorting, which is faster here than hashing."""
    codes = np.sort(codes)
    new = np.ones(len(codes), bool)
    new[1:] = codes[1:] != codes[:-1]
    return codes[new]


def ranges(work: np.ndarray, limit: int) -> Iterator[tuple[int, int]]:
    """Ranges of places whose work sums to limit at most, or single ones with more."""
    upto, a = np.cumsum(work), 0
    while a < len(work):
        b = int(np.searchsorted(upto, (upto[a - 1] if a else 0) + limit, "right"))
        b = min(max(b, a + 1), len(work))
        yield a, b
        a = b


class ItemIndex:
    """Postings of test items by term and block, with block-max weights."""

    def __init__(self, items: list[tuple[int, str]], threshold: float, min_words: int, whole: dict | None = None):
        words = [(i, t, hashed_words(t or "")) for i, t in items]
        kept = [x for x in words if len(x[2]) >= min_words]
        self.ids = [i for i, _, _ in kept]
        #: width -> (sorted codes of short items, their ids)
        self.short = {}
        for width in sorted({len(w) for _, _, w in words if 0 < len(w) < min_words}):
            found = [(int(grams(w, width)[0]), i) for i, _, w in words if len(w) == width]
            found.sort(key=lambda x: x[0])
            self.short[width] = np.array([c for c, _ in found], np.uint64), [i for _, i in found]
        self.threshold = threshold
        n = len(kept)
        self.blocks = -(-n // BLOCK_ITEMS)
        counts = [Counter(w.tolist()) for _, _, w in kept]
        df = Counter(t for c in counts for t in c)
        self.terms = np.array(sorted(df), np.uint64)
        rank = {int(t): k for k, t in enumerate(self.terms)}
        lengths = [len(w) for _, _, w in kept]
        whole = whole or {"n": n, "tokens": sum(lengths), "longest": max(lengths, default=1), "df": df}
        n, df = whole["n"], whole["df"]
        idf = {t: float(np.log(1 + (n - d + 0.5) / (d + 0.5))) for t, d in df.items()}
        mean = whole["tokens"] / max(n, 1)
        self.stride, self.lengths = whole["longest"], lengths
        rows = []
        for item, (c, length) in enumerate(zip(counts, lengths, strict=True)):
            raw = {t: idf[t] * f * (K1 + 1) / (f + K1 * (1 - B + B * length / mean)) for t, f in c.items()}
            own = sum(raw.values())
            rows += [(rank[t], item // BLOCK_ITEMS, item, v / own) for t, v in raw.items()]
        rows.sort()
        table = np.array(rows, np.float64).reshape(-1, 4)
        self.post_term, self.post_block, self.post_item = (table[:, k].astype(np.int64) for k in range(3))
        self.post_weight = table[:, 3]
        if len(rows):
            head = np.flatnonzero(np.r_[True, (np.diff(self.post_term) != 0) | (np.diff(self.post_block) != 0)])
            term = self.post_term[head]
            self.group_max, self.group_block = np.maximum.reduceat(self.post_weight, head), self.post_block[head]
            self.group_key, self.group_first = term * self.blocks + self.group_block, np.append(head, len(rows))
            self.term_first = np.searchsorted(term, np.arange(len(self.terms) + 1))
            self.most = np.maximum.reduceat(self.group_max, self.term_first[:-1])
        self.sieve = np.zeros(1 << 16, bool)
        self.sieve[(self.terms & np.uint64(0xFFFF)).astype(np.int64)] = True
        self.parts = []
        for _, text, _ in kept:
            both = []
            for part in question_and_answer(text):
                words = hashed_words(part)
                width = min(GRAM, len(words))
                less = min(width, max(1, len(words) // SHARE))
                both.append(tuple((w, np.unique(grams(words, w)) if w else np.zeros(0, np.uint64)) for w in (width, less)))
            self.parts.append(both)

    def term_ids(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(positions that hold a term, its number)."""
        spots = np.flatnonzero(self.sieve[(hashes & np.uint64(0xFFFF)).astype(np.int64)])
        found = np.minimum(np.searchsorted(self.terms, hashes[spots]), len(self.terms) - 1)
        hit = self.terms[found] == hashes[spots]
        return spots[hit], found[hit]

    def retrieve(self, words: WordChunk) -> Iterator[tuple[int, int, float]]:
        """(document, item, best score) for all passages at or above the threshold."""
        if not len(self.ids) or not len(words.hashes):
            return
        spots, term = self.term_ids(words.hashes)
        count = np.diff(words.first)
        pieces = np.maximum(1, -(-count // self.stride))
        piece_first = np.concatenate([[0], np.cumsum(pieces)])
        doc = np.searchsorted(words.first, spots, "right") - 1
        piece = piece_first[doc] + (spots - words.first[doc]) // self.stride
        pairs = distinct(piece * len(self.terms) + term)
        piece, term = pairs // len(self.terms), pairs % len(self.terms)
        # A passage is a piece and the next one of the same document.
        piece_doc = np.repeat(np.arange(len(pieces)), pieces)
        end = np.arange(1, len(piece_doc) + 1) + np.append(piece_doc[1:] == piece_doc[:-1], False)
        lo, hi = np.searchsorted(piece, np.arange(len(end))), np.searchsorted(piece, end)
        best: dict[tuple[int, int], float] = {}
        for begin, stop in ranges(hi - lo, TERMS_AT_ONCE):
            for passage, block in self.candidates(term, lo[begin:stop], hi[begin:stop]):
                scores = self.scores(term, lo[begin + passage], hi[begin + passage], block)
                for i, j in zip(*np.nonzero(scores >= self.threshold), strict=True):
                    key = (int(piece_doc[begin + passage[i]]), int(block[i] * BLOCK_ITEMS + j))
                    best[key] = max(best.get(key, 0.0), float(scores[i, j]))
        for (d, item), score in best.items():
            yield d, item, score

    def terms_of(self, term: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(passage, term) of the different terms in term[lo[i]:hi[i]]."""
        passage, at = spread(lo, hi - lo)
        pairs = distinct(passage * len(self.terms) + term[at])
        return pairs // len(self.terms), pairs % len(self.terms)

    def candidates(self, term: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(passage, block) whose bound reaches the threshold, some at a time.

        The terms of a passage that weigh least in any item go first; up to the pivot, where their largest weights
        sum to SKIPPED of the threshold, their postings are not read and count with that sum.
        """
        passage, terms = self.terms_of(term, lo, hi)
        order = np.lexsort((self.most[terms], passage))
        passage, terms = passage[order], terms[order]
        upto = np.cumsum(self.most[terms])
        first = np.searchsorted(passage, np.arange(len(lo)))
        before = np.concatenate([[0.0], upto])[first]
        driving = upto - before[passage] > SKIPPED * self.threshold
        skipped = np.bincount(passage[~driving], self.most[terms[~driving]], minlength=len(lo))
        passage, terms = passage[driving], terms[driving]
        size = self.term_first[terms + 1] - self.term_first[terms]
        work = np.bincount(passage, size, minlength=len(lo)).astype(np.int64) + self.blocks
        edge = np.searchsorted(passage, np.arange(len(lo) + 1))
        for a, b in ranges(work, POSTINGS_AT_ONCE):
            mine = slice(edge[a], edge[b])
            which, group = spread(self.term_first[terms[mine]], size[mine])
            bound = np.bincount((passage[mine][which] - a) * self.blocks + self.group_block[group], self.group_max[group], minlength=(b - a) * self.blocks).reshape(b - a, self.blocks)
            opened, block = np.nonzero((bound > 0) & (bound + skipped[a:b, None] >= self.threshold - ROUNDING))
            for k in range(0, len(opened), OPEN_AT_ONCE):
                yield opened[k : k + OPEN_AT_ONCE] + a, block[k : k + OPEN_AT_ONCE]

    def scores(self, term: np.ndarray, lo: np.ndarray, hi: np.ndarray, block: np.ndarray) -> np.ndarray:
        """Full scores of the items of blocks for passages of the terms lo to hi; blocks whose largest weights of all terms stay below are not opened."""
        opened, terms = self.terms_of(term, lo, hi)
        wanted = terms * self.blocks + block[opened]
        found = np.minimum(np.searchsorted(self.group_key, wanted), len(self.group_key) - 1)
        hit = self.group_key[found] == wanted
        opened, found = opened[hit], found[hit]
        keep = np.bincount(opened, self.group_max[found], minlength=len(lo))[opened] >= self.threshold - ROUNDING
        opened, found = opened[keep], found[keep]
        which, post = spread(self.group_first[found], self.group_first[found + 1] - self.group_first[found])
        slot = opened[which] * BLOCK_ITEMS + self.post_item[post] % BLOCK_ITEMS
        return np.bincount(slot, self.post_weight[post], minlength=len(lo) * BLOCK_ITEMS).reshape(-1, BLOCK_ITEMS)

    def overlaps(self, words: np.ndarray, item: int) -> list[float]:
        """Shares of the question's and of the answer's n-grams that the text holds."""
        parts = self.parts[item]
        held = [grams(words, width) for (width, _), _ in parts]
        out = [float(np.isin(codes, g).mean()) if len(codes) else 1.0 for ((_, codes), _), g in zip(parts, held, strict=True)]
        for k, (full, less) in enumerate(parts):
            if less[0] == full[0] or out[k] == 1.0:
                continue
            hits = np.flatnonzero(np.isin(held[1 - k], parts[1 - k][0][1]))
            near = np.zeros(len(words) + 1, np.int64)
            np.add.at(near, np.maximum(hits - self.lengths[item], 0), 1)
            np.add.at(near, np.minimum(hits + self.lengths[item] + GRAM, len(words)), -1)
            code = grams(words, less[0])
            code = code[np.cumsum(near)[: len(code)] > 0]
            out[k] = max(out[k], float(np.isin(less[1], code).mean()))
        return out

    def whole_items(self, words: WordChunk) -> Iterator[tuple[int, int | None]]:
        """(document, item id) of the items of fewer than min_words words that a document holds."""
        doc = words.doc_of_word()
        for width, (codes, ids) in self.short.items():
            code = grams(words.hashes, width)
            spots = np.flatnonzero(np.isin(code, codes))
            spots = spots[doc[spots] == doc[spots + width - 1]]
            lo, hi = np.searchsorted(codes, code[spots]), np.searchsorted(codes, code[spots], "right")
            pairs = {(int(d), k) for d, a, b in zip(doc[spots], lo, hi, strict=True) for k in range(a, b)}
            for d, k in sorted(pairs):
                yield d, ids[k]

    def leaks(self, column: pa.Array, overlap: float) -> Iterator[tuple[int, int, float, float, float]]:
        """(row, item id, score, question overlap, answer overlap) that are verified."""
        for lo, _, words in word_chunks(column, alnum=True):
            for d, item, score in self.retrieve(words):
                q, a = self.overlaps(words.hashes[words.first[d] : words.first[d + 1]], item)
                if q >= overlap and a >= overlap:
                    yield lo + d, self.ids[item], score, q, a
            for d, item in self.whole_items(words):
                yield lo + d, item, 1.0, 1.0, 1.0


def term_counts(items: DataFrame, min_words: int) -> DataFrame:
    """term, df: the number of items of min_words words or more that hold it; the null term's row has their number, tokens and longest."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept = [w for t in batch.column(0).to_pylist() if len(w := hashed_words(t or "")) >= min_words]
            if kept:
                term, df = np.unique(np.concatenate([np.unique(w) for w in kept]), return_counts=True)
                size, none = [len(w) for w in kept], [None] * len(term)
                columns = ([*term.view(np.int64).tolist(), None], [*df.tolist(), len(kept)], [*none, sum(size)], [*none, max(size)])
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["term", "df", "tokens", "longest"])

    parts = items.select("text").mapInArrow(tidy(count), "term bigint, df bigint, tokens bigint, longest bigint")
    return parts.groupBy("term").agg(F.sum("df").alias("df"), F.sum("tokens").alias("tokens"), F.max("longest").alias("longest"))


def indexes(benchmark: DataFrame, threshold: float, min_words: int) -> Iterator[ItemIndex]:
    """Indexes of SLICE items at most; the driver holds one at a time."""
    items = benchmark.select("item_id", "text")
    total = items.count()
    slices = -(-total // SLICE)
    counts = written(term_counts(items, min_words), "terms") if slices > 1 else None
    for k in range(slices):
        part = items.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(slices)) == k) if slices > 1 else items
        whole = None
        if slices > 1:
            mine = counts.join(term_counts(part, min_words).select("term"), "term", "left_semi").collect()
            sums = counts.filter("term is null").collect()
            if sums:
                whole = {"n": sums[0]["df"], "tokens": sums[0]["tokens"], "longest": sums[0]["longest"], "df": {r["term"] % 2**64: r["df"] for r in mine}}
        index = ItemIndex(sorted(((r["item_id"], r["text"]) for r in part.collect()), key=lambda x: (x[0] is None, x[0] or 0, x[1] or "")), threshold, min_words, whole)
        forget_powers()
        yield index


def find_leaks(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.5, overlap: float = 0.5, min_words: int = 5) -> DataFrame:
    """op5: a row for each document and item it holds: doc_id, item_id, score, question_overlap, answer_overlap."""
    schema = "doc_id bigint, item_id bigint, score double, question_overlap double, answer_overlap double"
    out = None
    for index in indexes(benchmark, threshold, min_words):

        def run(batches: Iterator[pa.RecordBatch], index: ItemIndex = index) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = list(index.leaks(batch.column(1), overlap))
                ids = batch.column(0).take(pa.array([r[0] for r in rows], pa.int64()))
                yield pa.RecordBatch.from_arrays([ids, *(pa.array([r[k] for r in rows], kind) for k, kind in ((1, pa.int64()), (2, pa.float64()), (3, pa.float64()), (4, pa.float64())))], names=["doc_id", "item_id", "score", "question_overlap", "answer_overlap"])

        found = docs.select("doc_id", "text").mapInArrow(tidy(run), schema)
        out = found if out is None else out.unionByName(found)
    return docs.sparkSession.createDataFrame([], schema) if out is None else out


def decontaminate_stage(docs: DataFrame, benchmark: DataFrame, threshold: float = 0.5, overlap: float = 0.5, min_words: int = 5) -> DataFrame:
    """documents -> documents that hold no item of the benchmark."""
    place = docs.columns.index("text")
    for index in indexes(benchmark, threshold, min_words):

        def run(batches: Iterator[pa.RecordBatch], index: ItemIndex = index) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                clean = np.ones(batch.num_rows, bool)
                clean[np.array([r[0] for r in index.leaks(batch.column(place), overlap)], np.int64)] = False
                yield batch.filter(pa.array(clean))

        docs = docs.mapInArrow(tidy(run), docs.schema)
    return docs
