"""LM scoring with a weighted backoff automaton.

Counts come from all learning documents. Every word, every n-gram and every
context that occurs in one is counted exactly and kept. Interpolated discounting
by the number of a context's different followers gives each n-gram a
log-probability and each context a backoff weight.

As an automaton: contexts are states, n-grams are arcs, and a failure arc leads
from a context to its shorter one at the cost of the backoff weight. All
documents of a block go through it together, left to right, each carrying its
state and its sum; long texts enter in pieces, warmed up on the words before.

Nothing about the corpus is held whole anywhere. Documents lie in blocks, bounded
in bytes and compressed; a block asks for the counts of its own words first, and
with them gets numbers for its words, small ones for frequent words. It then asks
for its pairs and, with their pair, its triples in these numbers, sorted and by
planes of bytes, which compresses; the answers, in the order asked, meet the block
again and make a small automaton there. A context that is common in the corpus, by
the counts of its words, is spread over parts of its followers, so that no task
counts it alone; the triples of a common pair are asked for by themselves.

Edge cases: a null text is empty and has the end token only; equal texts have
equal scores; without learning documents every probability is the base's, with
one unseen type; a null doc_id learns (crc32 of it is null); a text longer than a
block is a block of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rankloom.llm.common import Scratch, forget_shuffles
from rankloom.llm.words import WordChunk, mix64, text_buffers, tidy, tidy_pair, tidy_table, word_chunks

ORDER, PIECE, ADD = 3, 512, 0.1
BLOCK_BYTES, ROW_BYTES, COMMON = 6 << 20, 64, 1 << 22
END = np.uint64(0x1F83D9ABFB41BD6B)
#: Texts are compressed once and moved twice.
TEXT_LEVEL = 6
#: Bytes of word numbers and counts in asks and replies.
WIDE = 6


def held_out(doc_id: Column) -> Column:
    """crc32 of doc_id as text, mod 10, is 0."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 10 == 0, F.lit(False))


def with_ends(words: WordChunk) -> tuple[np.ndarray, np.ndarray]:
    """(tokens with an end token behind each document, first token of each document)."""
    count = np.diff(words.first)
    first = words.first + np.arange(words.docs + 1)
    out = np.full(len(words.hashes) + words.docs, END, np.uint64)
    out[np.arange(len(words.hashes)) + np.repeat(np.arange(words.docs), count)] = words.hashes
    return out, first


def in_planes(values: np.ndarray, width: int = WIDE) -> bytes:
    """Byte after byte of all values, which compresses where high bytes are zero."""
    return np.ascontiguousarray(values.astype(np.int64).view(np.uint8).reshape(len(values), 8)[:, :width].T).tobytes()


def packed(parts: list[np.ndarray]) -> bytes:
    return pa.compress(b"".join(in_planes(x) for x in parts), "zstd", asbytes=True)


def unpacked(data: bytes, sizes: list[int]) -> list[np.ndarray]:
    """The arrays of given sizes that were packed together."""
    raw = np.frombuffer(pa.decompress(data, WIDE * sum(sizes), "zstd", asbytes=True), np.uint8)
    out, at = [], 0
    for n in sizes:
        wide = np.zeros((n, 8), np.uint8)
        wide[:, :WIDE] = raw[at : at + WIDE * n].reshape(WIDE, n).T
        out.append(wide.reshape(-1).view(np.int64))
        at += WIDE * n
    return out


def unique_inverse(key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(different keys in order, place of each key among them, some place of each different key)."""
    order = np.argsort(key)
    ordered = key[order]
    new = np.ones(len(key), bool)
    new[1:] = ordered[1:] != ordered[:-1]
    back = np.empty(len(key), np.int32)
    back[order] = np.cumsum(new, dtype=np.int32) - 1
    return ordered[new], back, order[new]


def ranges(first: np.ndarray, size: np.ndarray) -> np.ndarray:
    """first, first + 1, ... of every range of a given size, one behind the other."""
    which = np.repeat(np.arange(len(first)), size)
    return np.arange(len(which)) + (first - (np.cumsum(size) - size))[which]


def power_of_two(n: int) -> int:
    return max(8, 1 << max(0, n - 1).bit_length())


# -- blocks ------------------------------------------------------------------------


def blocks_of(docs: DataFrame) -> DataFrame:
    """documents -> block, doc_id, held, size (bytes) lists and the texts, compressed together."""

    def bundle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0

        def row() -> pa.RecordBatch:
            table = pa.Table.from_batches(held)
            as_list = lambda x: pa.ListArray.from_arrays(pa.array([0, len(x)], pa.int32()), x)
            buffers = [text_buffers(chunk) for chunk in table["text"].chunks]
            texts = b"".join(data[offsets[0] : offsets[-1]].tobytes() for data, offsets in buffers)
            sizes = np.concatenate([np.diff(offsets) for _, offsets in buffers])
            lists = [as_list(x) for x in (*(pa.concat_arrays(table[c].chunks) for c in ("doc_id", "held")), pa.array(sizes, pa.int64()))]
            return pa.RecordBatch.from_arrays([pa.array([table["id"][0].as_py()]), *lists, pa.array([pa.Codec("zstd", compression_level=TEXT_LEVEL).compress(texts, asbytes=True)])], names=["block", "doc_id", "held", "size", "texts"])

        for batch in batches:
            offsets = text_buffers(batch.column(3))[1]
            offsets = offsets + ROW_BYTES * np.arange(len(offsets))
            lo = 0
            while lo < batch.num_rows:
                hi = int(np.searchsorted(offsets, offsets[lo] + BLOCK_BYTES - size, "right")) - 1
                hi = min(max(hi, lo + (not held)), batch.num_rows)
                if hi > lo:
                    held.append(batch.slice(lo, hi - lo))
                    size += int(offsets[hi] - offsets[lo])
                if hi < batch.num_rows:
                    yield row()
                    held, size = [], 0
                lo = hi
        if held:
            yield row()

    rows = docs.select(F.monotonically_increasing_id().alias("id"), F.col("doc_id").cast("long"), held_out(F.col("doc_id")).alias("held"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.mapInArrow(tidy(bundle), "block bigint, doc_id array<bigint>, held array<boolean>, size array<bigint>, texts binary")


class BlockWords:
    """Tokens of one block: codes (its different words in order), word (token -> place in codes), first token of each document."""

    def __init__(self, held: np.ndarray, size: np.ndarray, texts: bytes):
        data = pa.decompress(texts, int(size.sum()), "zstd") if len(size) else pa.py_buffer(b"")
        column = pa.LargeStringArray.from_buffers(len(size), pa.py_buffer(np.concatenate([[0], np.cumsum(size)]).astype(np.int64)), data)
        tokens, first, done = [], [np.zeros(1, np.int64)], 0
        for _, _, words in word_chunks(column):
            part, begin = with_ends(words)
            tokens.append(part)
            first.append(begin[1:] + done)
            done += len(part)
        self.first = np.concatenate(first)
        self.learns = np.repeat(~held, np.diff(self.first))
        self.codes, self.word, _ = unique_inverse(np.concatenate(tokens) if tokens else np.zeros(0, np.uint64))

    @classmethod
    def of(cls, row: dict) -> BlockWords:
        return cls(np.array(row["held"], bool), np.array(row["size"], np.int64), row["texts"])

    def edges(self, cells: int) -> np.ndarray:
        """The words of each cell, which is a range of codes."""
        bounds = np.arange(1, cells, dtype=np.uint64) << np.uint64(65 - cells.bit_length())
        return np.concatenate([[0], np.searchsorted(self.codes, bounds), [len(self.codes)]])

    def asks(self, block: int, cells: int) -> list[tuple]:
        """(block, kind, cell, contexts, grams, inner, data) for each cell: words as differences of their codes, and their learning occurrences."""
        n = np.bincount(self.word[self.learns], minlength=len(self.codes))
        edges, out = self.edges(cells), []
        for cell in np.flatnonzero(np.diff(edges)):
            lo, hi = edges[cell : cell + 2]
            codes = np.diff(self.codes[lo:hi], prepend=np.uint64(0))
            data = pa.compress(np.ascontiguousarray(codes.view(np.uint8).reshape(-1, 8).T).tobytes() + in_planes(n[lo:hi]), "zstd", asbytes=True)
            out.append((block, 0, cell, 0, hi - lo, 0, data))
        return out


class BlockGrams:
    """Pairs and triples of a block whose words have their corpus counts and numbers.

    Words are placed by number. kinds[k] holds the n-grams of k + 2 words, ordered
    by context and last word: at (token -> n-gram or -1), n (learning occurrences), shorter
    (the n-gram without its first word), word (the last one), size (n-grams of each
    context), context (each context as an n-gram one shorter).
    """

    def __init__(self, words: BlockWords, counts: np.ndarray, number: np.ndarray):
        order = np.argsort(number)
        place = np.empty(len(order), np.int32)
        place[order] = np.arange(len(order), dtype=np.int32)
        self.first, self.counts, self.number = words.first, counts[order], number[order]
        self.word = place[words.word] if len(order) else words.word
        inside = np.arange(len(self.word)) - np.repeat(self.first[:-1], np.diff(self.first))
        self.kinds, shorter = [], self.word
        for k in range(2, ORDER + 1):
            spots = np.flatnonzero(inside >= k - 1)
            key = shorter[spots - 1].astype(np.int64) * len(order) + self.word[spots]
            key, back, some = unique_inverse(key)
            context, word = key // max(1, len(order)), (key % max(1, len(order))).astype(np.int32)
            head = np.flatnonzero(np.diff(context, prepend=-1))
            at = np.full(len(self.word), -1, np.int32)
            at[spots] = back
            kind = {"at": at, "n": np.bincount(back[words.learns[spots]], minlength=len(key)), "shorter": shorter[spots[some]], "word": word, "context": context[head], "size": np.diff(np.append(head, len(key)))}
            self.kinds.append(kind)
            shorter = at

    def first_words(self, k: int) -> list[np.ndarray]:
        """The words of each context of kinds[k], each by its place."""
        context = self.kinds[k]["context"]
        if k == 0:
            return [context]
        below = self.kinds[0]
        owner = np.repeat(below["context"], below["size"])
        return [owner[context], below["word"][context].astype(np.int64)]

    def parts(self, k: int, total: int) -> np.ndarray:
        """Into how many parts the followers of each context go: more for those expected to be common."""
        words = self.first_words(k)
        expected = self.counts[words[0]].astype(float)
        for w in words[1:]:
            expected = np.minimum(np.minimum(expected, self.counts[w]), 8 * expected * self.counts[w] / max(1, total))
        return 1 + (expected / COMMON).astype(np.int64)

    def lines(self, k: int, cells: int, total: int, least: int = 1) -> tuple[np.ndarray, ...]:
        """How the n-grams of contexts with least parts or more go to cells: (context, part and cell of each line, n-grams by line, their number in each line).

        A line is a part of a context; every part is asked for, as the followers in all parts make those of the context.
        """
        kind, parts = self.kinds[k], self.parts(k, total)
        parts = np.where(parts >= least, parts, 0)
        hashed = np.zeros(len(parts), np.uint64)
        for w in self.first_words(k):
            hashed = mix64(hashed * np.uint64(0x9E3779B97F4A7C15) + self.number[w].view(np.uint64) + np.uint64(1))
        begin = np.cumsum(parts) - parts
        context = np.repeat(np.arange(len(parts)), parts)
        part = np.arange(len(context)) - begin[context]
        cell = (mix64(hashed[context] + part.astype(np.uint64)) >> np.uint64(65 - cells.bit_length())).astype(np.int64)
        owner = np.repeat(np.arange(len(parts)), kind["size"])
        mine = np.flatnonzero(parts[owner])
        owner = owner[mine]
        line = begin[owner]
        split = np.flatnonzero(parts[owner] > 1)
        spread = mix64(self.number[kind["word"][mine[split]]].view(np.uint64) + np.uint64(7)) % parts[owner[split]].astype(np.uint64)
        line[split] += spread.astype(np.int64)
        small = np.uint16 if cells <= 1 << 16 else np.int64
        by_cell = np.argsort(cell.astype(small), kind="stable")
        rank = np.empty(len(by_cell), np.int64)
        rank[by_cell] = np.arange(len(by_cell))
        grams = np.argsort(rank[line], kind="stable") if len(split) else np.argsort(cell[line].astype(small), kind="stable")
        return context[by_cell], part[by_cell], cell[by_cell], mine[grams], np.bincount(rank[line], minlength=len(by_cell))

    def riding(self, grams: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
        """(triples of each pair of grams, these triples) for pairs that are no common context: they go along with their pair."""
        kind = self.kinds[1]
        size, first = (np.zeros(len(self.kinds[0]["word"]), np.int64) for _ in range(2))
        size[kind["context"]] = np.where(self.parts(1, total) == 1, kind["size"], 0)
        first[kind["context"]] = np.cumsum(kind["size"]) - kind["size"]
        return size[grams], ranges(first[grams], size[grams])

    def asks(self, block: int, cells: int, total: int) -> list[tuple]:
        """Rows as of words: contexts by their words, and followers with their learning occurrences; pairs with their triples."""
        out = []
        for k, kind in enumerate(self.kinds):
            context, part, cell, grams, size = self.lines(k, cells, total, 1 if k == 0 else 2)
            words = [*(self.number[w][context] for w in self.first_words(k)), part]
            follower, n = self.number[kind["word"]][grams], kind["n"][grams]
            triples, inner = self.riding(grams, total) if k == 0 else (np.zeros(len(grams), np.int64), grams[:0])
            last, m = self.number[self.kinds[1]["word"]][inner], self.kinds[1]["n"][inner]
            line_edge, upto, within = np.searchsorted(cell, np.arange(cells + 1)), np.concatenate([[0], np.cumsum(size)]), np.concatenate([[0], np.cumsum(triples)])
            for c in np.flatnonzero(np.diff(line_edge)):
                lo, hi = line_edge[c : c + 2]
                a, b = upto[lo], upto[hi]
                i, j = within[a], within[b]
                data = [np.diff(words[0][lo:hi], prepend=0), *(w[lo:hi] for w in words[1:]), size[lo:hi], follower[a:b], n[a:b], triples[a:b], last[i:j], m[i:j]]
                out.append((block, k + 1, c, hi - lo, b - a, j - i, packed(data)))
        return out

    def answers(self, replies: list[list[dict]], cells: int, total: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """For each of kinds (corpus count of each n-gram, followers of each context)."""
        n, followers = ([np.zeros(len(k[x]), np.int64) for k in self.kinds] for x in ("word", "size"))
        joined = lambda x: np.concatenate(x) if x else np.zeros(0, np.int64)
        for k in range(ORDER - 1):
            context, _, _, grams, _ = self.lines(k, cells, total, 1 if k == 0 else 2)
            got = [unpacked(r["data"], [r["grams"], r["contexts"], r["grams"], r["inner"]]) for r in sorted(replies[k], key=lambda r: r["cell"])]
            count, mine, next_followers, inner = (joined([g[i] for g in got]) for i in range(4))
            n[k][grams] = count
            followers[k] += np.bincount(context, mine, minlength=len(followers[k])).astype(np.int64)
            if k == 0:
                n[1][self.riding(grams, total)[1]] = inner
                of_pair = np.zeros(len(n[0]), np.int64)
                of_pair[grams] = next_followers
                followers[1] += of_pair[self.kinds[1]["context"]]
        return list(zip(n, followers, strict=True))


ASKS = "block bigint, kind int, cell int, contexts bigint, grams bigint, inner bigint, data binary"


def as_table(rows: list[tuple]) -> pa.Table:
    kinds = (pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary())
    columns = list(zip(*rows, strict=True)) if rows else [()] * len(kinds)
    return pa.table([pa.array([int(x) if i < 6 else x for x in c], kind) for i, (c, kind) in enumerate(zip(columns, kinds, strict=True))], names=["block", "kind", "cell", "contexts", "grams", "inner", "data"])


# -- cells: counts of the corpus ---------------------------------------------------


def number_words(cells: int, table: pa.Table) -> pa.Table:
    """Asks of all blocks for the words of a cell -> to each block counts and numbers, in its order.

    The first row has the types and tokens of the cell.
    """
    cell, codes, n = table["cell"][0].as_py(), [], []
    for grams, ask in zip(table["grams"].to_pylist(), table["data"].to_pylist(), strict=True):
        raw = pa.decompress(ask, (8 + WIDE) * grams, "zstd", asbytes=True)
        codes.append(np.cumsum(np.ascontiguousarray(np.frombuffer(raw[: 8 * grams], np.uint8).reshape(8, grams).T).reshape(-1).view(np.uint64), dtype=np.uint64))
        wide = np.zeros((grams, 8), np.uint8)
        wide[:, :WIDE] = np.frombuffer(raw[8 * grams :], np.uint8).reshape(WIDE, grams).T
        n.append(wide.reshape(-1).view(np.int64))
    known, back, _ = unique_inverse(np.concatenate(codes))
    total = np.bincount(back, np.concatenate(n), minlength=len(known)).astype(np.int64)
    number = np.empty(len(known), np.int64)
    number[np.argsort(-total, kind="stable")] = np.arange(len(known)) * cells + cell
    upto = np.cumsum([len(c) for c in codes])
    replies = [packed([total[back[b - len(c) : b]], number[back[b - len(c) : b]]]) for c, b in zip(codes, upto, strict=True)]
    rest = [0] * (len(replies) - 1)
    table = table.drop_columns(["data"]).append_column("data", pa.array(replies, pa.binary()))
    return table.append_column("types", pa.array([int((total > 0).sum()), *rest], pa.int64())).append_column("tokens", pa.array([int(total.sum()), *rest], pa.int64()))


def followed(contexts: np.ndarray, size: np.ndarray, follower: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Contexts by code, each with size followers and their occurrences -> (code and count of each n-gram, followers seen of each context)."""
    _, line, _ = unique_inverse(contexts)
    code = mix64(np.repeat(contexts, size) * np.uint64(0x9E3779B97F4A7C15) + follower)
    _, back, some = unique_inverse(code)
    total = np.bincount(back, n, minlength=len(some)).astype(np.int64)
    owner = np.repeat(line, size)
    seen = np.bincount(owner[some], total > 0, minlength=int(line.max(initial=-1)) + 1).astype(np.int64)
    return code, total[back], seen[line]


def count_grams(table: pa.Table) -> pa.Table:
    """Asks of all blocks for one kind and cell -> to each block, in its order, n by n-gram, followers by line, followers of pairs and n by triple."""
    kind = table["kind"][0].as_py()
    contexts, grams, inner = (table[c].to_pylist() for c in ("contexts", "grams", "inner"))
    lines, size, follower, n, triples, last, m = ([] for _ in range(7))
    for c, g, t, ask in zip(contexts, grams, inner, table["data"].to_pylist(), strict=True):
        first, *rest, sizes, f, x, own, w, y = unpacked(ask, [c] * (kind + 2) + [g, g, g, t, t])
        code = mix64(np.cumsum(first).view(np.uint64) + np.uint64(1))
        for word in rest:
            code = mix64(code * np.uint64(0x9E3779B97F4A7C15) + word.view(np.uint64))
        for held, values in ((lines, code), (size, sizes), (follower, f.view(np.uint64)), (n, x), (triples, own), (last, w.view(np.uint64)), (m, y)):
            held.append(values)
    lines, size, follower, n, triples, last, m = (np.concatenate(x) for x in (lines, size, follower, n, triples, last, m))
    pair, total, line_of = followed(lines, size, follower, n)
    # A pair is the context of its triples.
    _, deeper, of_pair = followed(pair, triples, last, m)
    c_end, g_end, t_end = np.cumsum(contexts), np.cumsum(grams), np.cumsum(inner)
    replies = [packed([total[g1 - g : g1], line_of[c1 - c : c1], of_pair[g1 - g : g1], deeper[t1 - t : t1]]) for c, c1, g, g1, t, t1 in zip(contexts, c_end, grams, g_end, inner, t_end, strict=True)]
    return table.drop_columns(["data"]).append_column("data", pa.array(replies, pa.binary()))


# -- the automaton -----------------------------------------------------------------


class Automaton:
    """States, arcs and failure arcs over the n-grams of one block.

    State 0 of each document has no context; a word or n-gram that learning documents go
    on from is the state of its last words. arc[k] and known[k] tell the log10 weight of
    an n-gram of k + 1 words and whether it is an arc; failure[k] and live[k] the log10 backoff
    mass of a context of k + 1 words and whether it is a state.
    """

    def __init__(self, grams: BlockGrams, answers: list[tuple[np.ndarray, np.ndarray]], floor: float):
        p, mass = (grams.counts + ADD) / floor, grams.counts
        self.grams, self.arc, self.known, self.failure, self.live = grams, [np.log10(p)], [np.ones(len(p), bool)], [], []
        for kind, (n, followers) in zip(grams.kinds, answers, strict=True):
            context = kind["context"]
            failure, live = np.zeros(len(mass)), np.zeros(len(mass), bool)
            live[context] = (mass[context] > 0) & (followers > 0)
            failure[context] = np.log10(np.maximum(followers, 1) / np.maximum(mass[context] + followers, 1))
            m, f = np.repeat(mass[context], kind["size"]), np.repeat(followers, kind["size"])
            below = p[kind["shorter"]]
            p = np.where(m > 0, (n + f * below) / np.maximum(m + f, 1), below)
            mass = n
            self.arc.append(np.log10(p))
            self.known.append(n > 0)
            self.failure.append(failure)
            self.live.append(live)

    def walk(self) -> np.ndarray:
        """Log10 probability of every document; one pass from left to right over all of them."""
        first, at = self.grams.first, [self.grams.word, *(k["at"] for k in self.grams.kinds)]
        count = np.diff(first)
        pieces = -(-count // PIECE)
        doc = np.repeat(np.arange(len(count)), pieces)
        part = np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        begin = first[doc] + part * PIECE
        warm = np.where(part > 0, ORDER - 1, 0)
        length = np.minimum(begin + PIECE, first[doc + 1]) - begin + warm
        order = np.argsort(-length, kind="stable")
        begin, warm, length, owner = begin[order], warm[order], length[order], doc[order]
        total = np.zeros(len(begin))
        state = [np.full(len(begin), -1, np.int32) for _ in range(ORDER - 1)]
        for t in range(int(length[0]) if len(length) else 0):
            live = int(np.searchsorted(-length, -t, "left"))
            pos = begin[:live] - warm[:live] + t
            gained, todo = np.zeros(live), np.ones(live, bool)
            for k in range(ORDER - 1, 0, -1):
                if not len(self.known[k]):
                    continue  # the block has no n-gram of k + 1 words, so no context of k words
                here = todo & (state[k - 1][:live] >= 0)
                gram = at[k][pos]
                hit = here & self.known[k][gram]
                gained += np.where(hit, self.arc[k][gram], 0)
                gained += np.where(here & ~hit, self.failure[k - 1][state[k - 1][:live]], 0)
                todo &= ~hit
            word = at[0][pos]
            gained += np.where(todo, self.arc[0][word], 0)
            total[:live] += np.where(t >= warm[:live], gained, 0)
            follows = t > 0
            for k in range(ORDER - 1):
                # The last k + 1 words, where they lie in the walker's text and learning documents go on from them.
                gram = at[k][pos]
                known = (gram >= 0) & (follows | (k == 0))
                state[k] = np.where(known & self.live[k][gram] if len(self.live[k]) else False, gram, -1).astype(np.int32)
        return np.bincount(owner, total, minlength=len(count))


SCORED = "doc_id bigint, held_out boolean, n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double"


def numbered(words: BlockWords, replies: list[dict]) -> BlockGrams:
    """The block's grams, with what the cells of its words replied."""
    got = [unpacked(r["data"], [r["grams"], r["grams"]]) for r in sorted(replies, key=lambda r: r["cell"])]
    none = np.zeros(0, np.int64)
    return BlockGrams(words, np.concatenate([x for x, _ in got]) if got else none, np.concatenate([x for _, x in got]) if got else none)


def score_texts(docs: DataFrame) -> DataFrame:
    """op8: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    scratch = Scratch(docs.sparkSession, "lm")
    blocks = scratch.written(blocks_of(docs), "blocks")
    cells = power_of_two(2 * blocks.count())

    def ask_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                yield from as_table(BlockWords.of(row).asks(row["block"], cells)).to_batches()

    def number(table: pa.Table) -> pa.Table:
        return number_words(cells, table)

    asked = blocks.select("block", "held", "size", "texts").mapInArrow(tidy(ask_words), ASKS)
    words = scratch.written(asked.groupBy("cell").applyInArrow(tidy_table(number), f"{ASKS}, types bigint, tokens bigint"), "words")
    n_total, types = (int(x or 0) for x in words.agg(F.sum("tokens"), F.sum("types")).collect()[0])
    floor = n_total + ADD * (types + 1)
    del asked
    forget_shuffles(docs.sparkSession)

    def ask_grams(block: pa.Table, replies: pa.Table) -> pa.Table:
        row = block.to_pylist()[0]
        return as_table(numbered(BlockWords.of(row), replies.to_pylist()).asks(row["block"], cells, n_total))

    def score(block: pa.Table, replies: pa.Table) -> pa.Table:
        row, got = block.to_pylist()[0], [[] for _ in range(ORDER)]
        for r in replies.to_pylist():
            got[r["kind"]].append(r)
        grams = numbered(BlockWords.of(row), got[0])
        model = Automaton(grams, grams.answers(got[1:], cells, n_total), floor)
        docs = len(row["doc_id"])
        doc = np.repeat(np.arange(docs), np.diff(grams.first))
        total = lambda w: np.bincount(doc, w, minlength=docs)
        columns = [pa.array(row["doc_id"], pa.int64()), pa.array(row["held"], pa.bool_()), pa.array(np.diff(grams.first)), pa.array(total(grams.counts[grams.word] > 0).astype(np.int64)), pa.array(np.full(docs, n_total)), pa.array(total(model.arc[0][grams.word])), pa.array(model.walk())]
        return pa.table(columns, names=[c.split()[0] for c in SCORED.split(", ")])

    at_block = blocks.select("block", "doc_id", "held", "size", "texts").groupBy("block")
    words = words.select(*(c.split()[0] for c in ASKS.split(", ")))
    asks = at_block.cogroup(words.groupBy("block")).applyInArrow(tidy_pair(ask_grams), ASKS)
    replies = asks.groupBy("kind", "cell").applyInArrow(tidy_table(count_grams), ASKS)
    return at_block.cogroup(words.unionByName(replies).groupBy("block")).applyInArrow(tidy_pair(score), SCORED)
