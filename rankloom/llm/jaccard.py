"""N-gram Jaccard join with a token-group matrix.

Every document becomes a set of word shingles. Documents of one set are one node.
Similar sets are partitioned into groups, first each alone, then the components of
the links found so far. The token-group matrix lists, for every rare-first prefix
token, the sets and groups that hold it; a set is a query against the groups of
its prefix tokens. Each group keeps a union of its members' tokens, folded to 256
counters (the largest of any member), which bounds a query's overlap with every
member from above. Only groups whose bound reaches the threshold are opened, and
an opened group's members are compared with the query on all tokens.

The prefix makes this exact: sets with Jaccard t share a token among the first
n - ceil(t n) + 1 of each under any common order of tokens, and behind the first
shared token both have at least their overlap left. The order puts frequent tokens
last (the LATE_TOKENS most frequent ones at most), then goes by hash.

Leader rounds compare each token's sets with some of them, which joins groups of
near copies at linear cost, until few find none; the last round takes up all that
is still apart. Before a pair is named, the sizes, the places of the token and the
parities of both sets' tokens in 128 classes must allow the similarity.

Edge cases: a null text is empty; a text without words has an empty set and no
links; fewer words than the width make one shingle; equal texts and repeated rows
are one node; a null doc_id takes part and counts last in component ids.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rankloom.llm.common import Scratch, written
from rankloom.llm.words import mix64, shingles, tidy, tidy_pair, tidy_table, word_chunks

LATE_TOKENS, OFTEN, LEADERS, CELL, SKETCH, PARITIES = 1 << 21, 8, 4, 512, 256, 128
#: Sets drawn as leaders for each token. Another leader round follows while MANY sets ask in vain and one of ENOUGH finds a link.
DRAWN, MANY, ENOUGH = 2, 1 << 15, 16
PAIR_BATCH, COUNTED_TOGETHER = 1 << 20, 8192


def binary_column(values: np.ndarray, first: np.ndarray) -> pa.Array:
    """Byte strings values[first[i]:first[i + 1]] as an Arrow column."""
    offsets = (first * values.itemsize).astype(np.int32)
    return pa.Array.from_buffers(pa.binary(), len(first) - 1, [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(values))])


def joined_bytes(column: pa.ChunkedArray | pa.Array, dtype: type) -> tuple[np.ndarray, np.ndarray]:
    """(all values, first of each row) of a binary column of numbers."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.binary())
    _, offsets, data = column.cast(pa.large_binary()).buffers()
    if not len(column):
        return np.zeros(0, dtype), np.zeros(1, np.int64)
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return np.frombuffer(raw.tobytes(), dtype), (offsets - offsets[0]) // np.dtype(dtype).itemsize


def spread(first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(range number, element) for all elements of ranges first, first + 1, ... of given sizes."""
    which = np.repeat(np.arange(len(first)), size)
    if not len(which):
        return which, which
    return which, np.arange(len(which)) + (first - np.concatenate([[0], np.cumsum(size)[:-1]]))[which]


def unique_pairs(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    new = np.ones(len(a), bool)
    new[1:] = (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    return a[new], b[new]


class JaccardJoin:
    """One run of the join over documents (doc_id, text)."""

    def __init__(self, docs: DataFrame, width: int = 4, percent: int = 85):
        self.docs, self.width, self.percent = docs.select("doc_id", "text"), width, percent
        self.spark = docs.sparkSession
        self.scratch = Scratch(self.spark, "jaccard")

    # -- sets and their prefixes -------------------------------------------------

    def frequent_tokens(self) -> np.ndarray:
        """Tokens to put last, LATE_TOKENS at most.

        Any set gives an exact join, so what some thousand rows hold once is not counted.
        Small input partitions are read together, or such tokens would be missed.
        """
        width = self.width

        def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, rows = [], 0

            def repeated() -> pa.RecordBatch:
                codes = np.concatenate(held)
                codes.sort()
                token, n = np.unique(codes[np.flatnonzero(codes[1:] == codes[:-1])], return_counts=True)
                return pa.RecordBatch.from_arrays([pa.array(token.view(np.int64)), pa.array(n.astype(np.int64) + 1)], names=["token", "n"])

            for batch in batches:
                held += [shingles(words, width)[1] for _, _, words in word_chunks(batch.column(0))]
                rows += batch.num_rows
                if rows >= COUNTED_TOGETHER:
                    yield repeated()
                    held, rows = [], 0
            if held:
                yield repeated()

        tasks = max(1, self.docs.count() // COUNTED_TOGETHER)
        table = self.docs.select("text").coalesce(tasks).mapInArrow(tidy(count), "token bigint, n bigint").groupBy("token").agg(F.sum("n").alias("n"))
        table = self.scratch.written(table.filter(F.col("n") >= OFTEN), "frequent")
        step = F.floor(F.log2("n") * 8).cast("int")
        least, held = None, 0
        for r in sorted(table.groupBy(step.alias("step")).agg(F.count("*").alias("c")).collect(), reverse=True):
            held += r["c"]
            if held > LATE_TOKENS:
                break
            least = r["step"]
        found = table.filter(step >= least if least is not None else F.lit(False)).select("token").toArrow()
        return np.sort(found["token"].to_numpy().view(np.uint64)) if found.num_rows else np.zeros(0, np.uint64)

    def sets(self) -> DataFrame:
        """rid, doc_id, n, k1, k2 (digest of the set), b0, b1 (parities of its tokens), prefix, sketch for each document."""
        last = self.spark.sparkContext.broadcast(self.frequent_tokens())
        width, percent = self.width, self.percent

        def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            frequent = last.value
            for batch in batches:
                for lo, hi, words in word_chunks(batch.column(2)):
                    doc, code = shingles(words, width)
                    docs = hi - lo
                    n = np.bincount(doc, minlength=docs)
                    first = np.concatenate([[0], np.cumsum(n)])
                    some = np.flatnonzero(n)
                    digest = np.zeros((2, docs), np.uint64)
                    if len(code):
                        digest[0, some] = np.add.reduceat(mix64(code), first[some])
                        digest[1, some] = np.add.reduceat(mix64(code ^ np.uint64(0x5851F42D4C957F2D)), first[some])
                    sketch = np.bincount(doc * SKETCH + (code >> np.uint64(56)).astype(np.int64), minlength=docs * SKETCH)
                    sketch = np.minimum(sketch, 65535).astype(np.uint16)
                    odd = np.bincount(doc * PARITIES + (code % np.uint64(PARITIES)).astype(np.int64), minlength=docs * PARITIES) & 1
                    odd = np.packbits(odd.astype(np.uint8)).view(np.int64).reshape(docs, 2)
                    at = np.minimum(np.searchsorted(frequent, code), max(len(frequent) - 1, 0))
                    late = (frequent[at] == code) if len(frequent) else np.zeros(len(code), bool)
                    order = np.argsort(doc * 2 + late, kind="stable")
                    length = n - (percent * n + 99) // 100 + (n > 0)
                    keep = (np.arange(len(code)) - first[doc]) < length[doc]
                    prefix = code[order][keep]
                    yield pa.RecordBatch.from_arrays(
                        [batch.column(0).slice(lo, docs), batch.column(1).slice(lo, docs), pa.array(n.astype(np.int64)), pa.array(digest[0].view(np.int64)), pa.array(digest[1].view(np.int64)), pa.array(odd[:, 0]), pa.array(odd[:, 1]), binary_column(prefix, np.concatenate([[0], np.cumsum(length)])), binary_column(sketch, np.arange(docs + 1) * SKETCH)],
                        names=["rid", "doc_id", "n", "k1", "k2", "b0", "b1", "prefix", "sketch"],
                    )

        rows = self.docs.select(F.monotonically_increasing_id().alias("rid"), "doc_id", "text")
        return self.scratch.written(rows.mapInArrow(tidy(make), "rid bigint, doc_id bigint, n bigint, k1 bigint, k2 bigint, b0 bigint, b1 bigint, prefix binary, sketch binary"), "sets")

    # -- the token-group matrix --------------------------------------------------

    def matrix(self, nodes: DataFrame) -> DataFrame:
        """nodes -> the lines (token, rid, n, left) of all prefix tokens that two sets or more hold, packed by a hash of the token.

        left counts the tokens of the set from this one on. A token that one set holds alone links nothing,
        in any round, so its line ends here.
        """
        cells, names = max(8, nodes.count() // 4096), ["token", "rid", "n", "left"]

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                token, first = joined_bytes(batch.column(2), np.uint64)
                size = np.diff(first)
                cell = (token % np.uint64(cells)).astype(np.int64)
                order = np.argsort(cell, kind="stable")
                begins = np.flatnonzero(np.diff(cell[order], prepend=-1))
                bounds = np.append(begins, len(token))
                rid, n = (batch.column(k).to_numpy() for k in range(2))
                left = np.repeat(n + first[:-1], size) - np.arange(len(token))
                columns = [token, np.repeat(rid, size), np.repeat(n, size).astype(np.int32), left.astype(np.int32)]
                yield pa.RecordBatch.from_arrays([pa.array(cell[order][begins].astype(np.int32)), *(binary_column(c[order], bounds) for c in columns)], names=["cell", *names])

        def shared(table: pa.Table) -> pa.Table:
            columns = [joined_bytes(table[c], kind)[0] for c, kind in zip(names, (np.uint64, np.int64, np.int32, np.int32), strict=True)]
            order = np.argsort(columns[0], kind="stable")
            token = columns[0][order]
            again = np.zeros(len(token), bool)
            again[1:] = token[1:] == token[:-1]
            again[:-1] |= again[1:]
            kept = order[again]
            return pa.table([table["cell"][:1], *(binary_column(c[kept], np.array([0, len(kept)])) for c in columns)], names=["cell", *names])

        schema = "cell int, " + ", ".join(f"{x} binary" for x in names)
        packed = nodes.select("rid", "n", "prefix").mapInArrow(tidy(pack), schema)
        return self.scratch.written(packed.groupBy("cell").applyInArrow(tidy_table(shared), schema), "matrix")

    def queries(self, matrix: DataFrame, nodes: DataFrame, leading: int | None) -> DataFrame:
        """(rid, grp): sets and groups that share a prefix token and can be similar by sizes, places and parities.

        leading: the number of a leader round, in which grp is the rid of a leader; None: all groups of the matrix are met.
        """
        percent = self.percent

        def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                token, first = joined_bytes(batch.column(1), np.uint64)
                rid, n, left = (joined_bytes(batch.column(k), kind)[0] for k, kind in ((2, np.int64), (3, np.int32), (4, np.int32)))
                cell = np.repeat(batch.column(0).to_numpy(), np.diff(first))
                yield pa.RecordBatch.from_arrays([pa.array(cell), pa.array(token.view(np.int64)), pa.array(rid), pa.array(n), pa.array(left)], names=["cell", "token", "rid", "n", "left"])

        def possible(x: np.ndarray, y: np.ndarray, row: dict[str, np.ndarray], line: dict[str, np.ndarray]) -> np.ndarray:
            """Whether row x can be similar to a member of line y."""
            n, low, high = row["n"][x], line["low"][y], line["high"][y]
            fits = (100 * n >= percent * low) & (100 * high >= percent * n)
            fits &= (100 + percent) * np.minimum(row["left"][x], line["left"][y]) >= percent * (n + low)
            # Parities in which all members of the line agree and the set does not: each is a token that one of two has alone.
            apart = sum(np.bitwise_count(((row[b][x] ^ line[b][y]) & line["all_" + b][y]).view(np.uint64)).astype(np.int64) for b in ("b0", "b1"))
            return fits & ((100 - percent) * (n + high) >= (100 + percent) * apart)

        def meet(table: pa.Table) -> pa.Table:
            row = {c: table[c].to_numpy() for c in ("token", "rid", "n", "left", "grp", "members", "b0", "b1")}
            own = row["rid"] if leading is not None else row["grp"]
            order = np.lexsort((own, row["token"]))
            row, own = {c: x[order].astype(np.int64) for c, x in row.items()}, own[order]
            new = np.ones(len(own), bool)
            new[1:] = row["token"][1:] != row["token"][:-1]
            run = np.cumsum(new) - 1
            if leading is not None:
                # Leaders are the sets that share most with others, the least changed of a group of copies, and some drawn for each token.
                _, place = np.unique(row["rid"], return_inverse=True)
                shared = -np.bincount(place, np.bincount(run)[run] - 1.0)[place]
                drawn = mix64((row["rid"] ^ row["token"]).view(np.uint64) + np.uint64(leading))
                begin = np.flatnonzero(new)[run]
                xs, gs = [], []
                for rank, leaders in ((shared, 0 if leading else LEADERS), (drawn, DRAWN)):
                    order = np.lexsort((row["rid"], rank, run))
                    mine = {c: x[order] for c, x in row.items()}
                    line = mine | {"low": mine["n"], "high": mine["n"], "all_b0": np.full(len(own), -1), "all_b1": np.full(len(own), -1)}
                    for k in range(leaders):
                        i = np.flatnonzero(np.arange(len(own)) - begin > k)
                        j = begin[i] + k
                        fits = (mine["grp"][i] != mine["grp"][j]) & possible(i, j, mine, line)
                        xs.append(mine["rid"][i[fits]])
                        gs.append(mine["rid"][j[fits]])
                x, g = unique_pairs(np.concatenate(xs), np.concatenate(gs))
            else:
                # Rows of a line: one token, one group. Each row meets the other lines of its token.
                head = new.copy()
                head[1:] |= own[1:] != own[:-1]
                at = np.flatnonzero(head)
                line = {"low": np.minimum.reduceat(row["n"], at), "high": np.maximum.reduceat(row["n"], at), "left": np.maximum.reduceat(row["left"], at)}
                for b in ("b0", "b1"):
                    line[b] = np.bitwise_and.reduceat(row[b], at)
                    line["all_" + b] = ~(line[b] ^ np.bitwise_or.reduceat(row[b], at))
                per_run = np.bincount(run[at], minlength=run[-1] + 1)
                line_first = np.concatenate([[0], np.cumsum(per_run)[:-1]])
                mixed = np.flatnonzero(per_run[run] > 1)
                xs, gs = [], []
                made = np.cumsum(per_run[run[mixed]])
                step = np.unique(np.r_[0, np.searchsorted(made, np.arange(PAIR_BATCH, made[-1] if len(made) else 0, PAIR_BATCH)), len(mixed)])
                for a, b in zip(step[:-1], step[1:], strict=True):
                    rows = mixed[a:b]
                    which, other = spread(line_first[run[rows]], per_run[run[rows]])
                    i, j = rows[which], at[other]
                    smaller = (row["members"][i] < row["members"][j]) | ((row["members"][i] == row["members"][j]) & (own[i] < own[j]))
                    fits = np.flatnonzero(smaller)
                    fits = fits[possible(i[fits], other[fits], row, line)]
                    x, g = unique_pairs(row["rid"][i[fits]], own[j[fits]])
                    xs.append(x)
                    gs.append(g)
                x, g = unique_pairs(np.concatenate(xs), np.concatenate(gs)) if xs else (np.zeros(0, np.int64),) * 2
            return pa.table({"rid": pa.array(x, pa.int64()), "grp": pa.array(g, pa.int64())})

        lines = matrix.mapInArrow(tidy(unpack), "cell int, token bigint, rid bigint, n int, left int")
        lines = lines.join(nodes.select("rid", "grp", "members", "b0", "b1"), "rid")
        return lines.groupBy("cell").applyInArrow(tidy_table(meet), "rid bigint, grp bigint").distinct()

    # -- bounds and opened groups ------------------------------------------------

    def unions(self, nodes: DataFrame) -> DataFrame:
        """grp, low (smallest set), union (largest count of each counter); tasks fold what they hold first."""

        def fold(grp: np.ndarray, low: np.ndarray, sketch: np.ndarray) -> list[pa.Array]:
            order = np.argsort(grp, kind="stable")
            head = np.flatnonzero(np.r_[True, np.diff(grp[order]) != 0])
            most = np.maximum.reduceat(sketch[order], head, axis=0)
            return [pa.array(grp[order][head]), pa.array(np.minimum.reduceat(low[order], head)), binary_column(most.reshape(-1), np.arange(len(head) + 1) * SKETCH)]

        def by_batch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if b.num_rows:
                    yield pa.RecordBatch.from_arrays(fold(b.column(0).to_numpy(), b.column(1).to_numpy(), joined_bytes(b.column(2), np.uint16)[0].reshape(-1, SKETCH)), names=["grp", "low", "union"])

        def by_group(table: pa.Table) -> pa.Table:
            sketch = joined_bytes(table["union"], np.uint16)[0].reshape(-1, SKETCH)
            return pa.table(fold(table["grp"].to_numpy(), table["low"].to_numpy(), sketch), names=["grp", "low", "union"])

        schema = "grp bigint, low bigint, union binary"
        alone = nodes.filter("members = 1").select("grp", F.col("n").alias("low"), F.col("sketch").alias("union"))
        large = nodes.filter("members > 1").select("grp", F.col("n").alias("low"), "sketch").mapInArrow(tidy(by_batch), schema)
        return alone.unionByName(large.groupBy("grp").applyInArrow(by_group, schema))

    def qualifying(self, asked: DataFrame, nodes: DataFrame) -> DataFrame:
        """The (rid, grp) whose union bound reaches the threshold."""
        percent = self.percent
        unions = self.unions(nodes.join(asked.select("grp").distinct(), "grp", "left_semi"))
        both = asked.join(nodes.select("rid", "n", "sketch"), "rid").join(unions, "grp")

        def bound(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                n, low = b.column(2).to_numpy(), b.column(3).to_numpy()
                mine, theirs = (joined_bytes(b.column(k), np.uint16)[0].reshape(-1, SKETCH) for k in (4, 5))
                most = np.minimum(np.minimum(mine, theirs).sum(1, dtype=np.int64), n)
                least = np.maximum(low, (percent * n + 99) // 100)
                full = (mine == 65535).any(1) | (theirs == 65535).any(1)
                keep = full | (100 * most >= percent * (n + np.maximum(least, most) - most))
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["rid", "grp"]).filter(pa.array(keep))

        return both.select("rid", "grp", "n", "low", "sketch", "union").mapInArrow(tidy(bound), "rid bigint, grp bigint")

    def opened(self, asked: DataFrame, nodes: DataFrame) -> DataFrame:
        """Links (a, b) between the query sets and the members of their groups, on all tokens."""
        asked = self.scratch.written(asked, "asked")
        groups = asked.groupBy("grp").agg(F.count("*").alias("askers"))
        members = self.scratch.written(nodes.select("rid", "grp", "members", "doc_id", "k1", "k2").join(groups, "grp"), "members")
        cut = lambda n: F.expr(f"int(ceil({n} / {CELL}))")
        wanted = members.select("rid", "doc_id", "k1", "k2").unionByName(nodes.join(asked.select("rid").distinct(), "rid", "left_semi").select("rid", "doc_id", "k1", "k2")).distinct()
        tokens = self.scratch.written(self.tokens_of(wanted), "tokens")
        piece = lambda n: F.pmod(F.xxhash64("rid"), cut(n)).cast("int")
        mine = members.select("grp", "rid", piece("members").alias("mpart"), F.explode(F.sequence(F.lit(0), cut("askers") - 1)).alias("qpart")).join(tokens, "rid")
        sizes = members.select("grp", "members", "askers").distinct()
        asks = asked.join(sizes, "grp").select("grp", "rid", piece("askers").alias("qpart"), F.explode(F.sequence(F.lit(0), cut("members") - 1)).alias("mpart"))
        asks = asks.withColumnRenamed("rid", "asker").join(tokens.select(F.col("rid").alias("asker"), F.col("codes").alias("asked_codes")), "asker")
        asks = asks.select("grp", "mpart", "qpart", "asker", "asked_codes")
        percent = self.percent

        def compare(queries: pa.Table, members: pa.Table) -> pa.Table:
            a, b = [], []
            if queries.num_rows and members.num_rows:
                codes, first = joined_bytes(members["codes"], np.uint64)
                size, rid = np.diff(first), members["rid"].to_numpy()
                owner = np.repeat(np.arange(len(size)), size)
                order = np.argsort(codes, kind="stable")
                codes, owner = codes[order], owner[order]
                asking, q_first = joined_bytes(queries["asked_codes"], np.uint64)
                q_rid = queries["asker"].to_numpy()
                lo, hi = np.searchsorted(codes, asking, "left"), np.searchsorted(codes, asking, "right")
                for q in range(len(q_rid)):
                    s = slice(q_first[q], q_first[q + 1])
                    _, at = spread(lo[s], (hi - lo)[s])
                    common = np.bincount(owner[at], minlength=len(size))
                    n = int(q_first[q + 1] - q_first[q])
                    linked = (100 * common >= percent * (n + size - common)) & (rid != q_rid[q])
                    a.append(np.full(int(linked.sum()), q_rid[q]))
                    b.append(rid[linked])
            join = lambda x: pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64())
            return pa.table({"a": join(a), "b": join(b)})

        pairs = asks.groupBy("grp", "mpart", "qpart").cogroup(mine.groupBy("grp", "mpart", "qpart")).applyInArrow(tidy_pair(compare), "a bigint, b bigint")
        return pairs

    def tokens_of(self, wanted: DataFrame) -> DataFrame:
        """rid, codes: all tokens of the wanted sets, taken from their documents again."""
        width = self.width

        def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lo, hi, words in word_chunks(batch.column(1)):
                    doc, code = shingles(words, width)
                    n = np.bincount(doc, minlength=hi - lo)
                    first = np.concatenate([[0], np.cumsum(n)])
                    some = np.flatnonzero(n)
                    digest = np.zeros((2, hi - lo), np.uint64)
                    if len(code):
                        digest[0, some] = np.add.reduceat(mix64(code), first[some])
                        digest[1, some] = np.add.reduceat(mix64(code ^ np.uint64(0x5851F42D4C957F2D)), first[some])
                    yield pa.RecordBatch.from_arrays([pa.array(digest[0].view(np.int64)), pa.array(digest[1].view(np.int64)), binary_column(code, first)], names=["k1", "k2", "codes"])

        ids = self.scratch.written(wanted.select(F.col("doc_id").alias("id")).distinct(), "ids")
        texts = self.docs.join(ids, F.expr("doc_id <=> id"), "left_semi")
        made = texts.mapInArrow(tidy(make), "k1 bigint, k2 bigint, codes binary").dropDuplicates(["k1", "k2"])
        return made.join(wanted.select("rid", "k1", "k2"), ["k1", "k2"]).select("rid", "codes")

    # -- the whole join ----------------------------------------------------------

    def components(self) -> DataFrame:
        """rid, doc_id, n, comp (a rid of its component), component_id of every document."""
        sets = self.sets()
        keys = ["k1", "k2", "n"]
        some = sets.filter("n > 0").select("rid", *keys)
        firsts = some.groupBy(*keys).agg(F.min("rid").alias("node"), F.count("*").alias("copies"))
        again = self.scratch.written(some.join(firsts.filter("copies > 1"), keys).filter("rid <> node").select("rid", "node"), "again")
        nodes = sets.filter("n > 0").join(again.select("rid"), "rid", "left_anti")
        alone = nodes.withColumn("grp", F.col("rid")).withColumn("members", F.lit(1).cast("long"))
        matrix = self.matrix(nodes)
        links, labels, grouped, leading = [], None, alone, 0
        while True:
            more, found, asking = self.round(matrix, grouped, grouped if leading is None else alone, leading)
            if found:
                links.append(more)
                labels = connected(reduce(DataFrame.unionByName, links), self.scratch)
            if leading is None:
                break
            if found:
                sizes = labels.groupBy("root").agg(F.count("*").alias("members"))
                grouped = nodes.join(self.scratch.written(labels.join(sizes, "root"), "labels"), "rid", "left")
                grouped = grouped.withColumn("grp", F.coalesce("root", "rid")).withColumn("members", F.coalesce("members", F.lit(1).cast("long"))).drop("root")
            leading = leading + 1 if asking - found > MANY and found * ENOUGH > asking else None
        keyed = sets.select("rid", "doc_id", "n").join(again, "rid", "left").withColumn("node", F.coalesce("node", "rid"))
        root = labels.withColumnRenamed("rid", "node") if labels is not None else keyed.select("node", F.col("node").alias("root")).distinct()
        keyed = keyed.join(root, "node", "left").select("rid", "doc_id", "n", F.coalesce("root", "node").alias("comp"))
        # Written, so that a join of a large component is one of two plain exchanges, which can be split.
        smallest = self.scratch.written(keyed.groupBy("comp").agg(F.min("doc_id").alias("component_id")), "smallest")
        out = written(keyed.join(smallest, "comp").select("rid", "doc_id", "n", "comp", "component_id"), "components")
        self.scratch.drop()
        return out

    def round(self, matrix: DataFrame, grouped: DataFrame, opening: DataFrame, leading: int | None) -> tuple[DataFrame, int, int]:
        """(links, sets that found one, sets that asked); opening: the nodes in the groups that are opened."""
        asked = self.scratch.written(self.queries(matrix, grouped, leading), "queries")
        links = self.scratch.written(self.opened(self.qualifying(asked, opening), opening), "links")
        return links, links.agg(F.countDistinct("a")).first()[0], asked.agg(F.countDistinct("rid")).first()[0]


def connected(links: DataFrame, scratch: Scratch) -> DataFrame:
    """links (a, b) -> rid, root (smallest rid) of all that have a link.

    Alternates two star steps until nothing moves: every node hands its larger
    neighbours to its smallest one, then its smaller ones. Each is one
    aggregation and one join; state is written in the shared folder.
    """
    ordered = lambda e: e.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u <> v").distinct()
    edges = scratch.written(ordered(links), "edges")
    seen = None
    while True:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
        large = ordered(large)
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u")
        small = small.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
        edges = scratch.written(ordered(small), "edges")
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).collect()[0]
        if tuple(state) == seen:
            return edges.select(F.col("u").alias("rid"), F.col("v").alias("root")).unionByName(edges.select(F.col("v").alias("rid"), F.col("v").alias("root"))).distinct()
        seen = tuple(state)


def jaccard_components(docs: DataFrame) -> DataFrame:
    """op3: doc_id, n_shingles, component_id."""
    return JaccardJoin(docs).components().select("doc_id", F.col("n").alias("n_shingles"), "component_id")


def dedupe_stage(docs: DataFrame) -> DataFrame:
    """documents -> of each component the row with the smallest doc_id, the first one of several; a null doc_id counts last.

    docs is scanned twice and must be a table: rows are told apart by their place in it.
    """
    rows = JaccardJoin(docs, width=5, percent=80).components()
    best = rows.groupBy("comp").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "rid")).alias("best"), F.count("*").alias("c")).filter("c > 1")
    best = written(best.select("comp", "best.rid").withColumnRenamed("rid", "first"), "best")
    gone = rows.join(best, "comp").filter("rid <> first").select(F.col("rid").alias("_rid"))
    return docs.withColumn("_place", F.monotonically_increasing_id()).join(gone, F.col("_place") == F.col("_rid"), "left_anti").select(*docs.columns)
