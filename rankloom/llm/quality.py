"""Quality classifier: a byte-level convolutional network in numpy.

A document is cut into chunks of CHUNK bytes. Learned filters of WIDTH bytes
move over a chunk in steps of STEP, run over into the next chunk by one step,
and are max-pooled for each chunk; a document's largest and mean pooled values
over all its chunks go into one logistic unit. The whole text is scored.

It is fitted on at most `per_class` labelled rows of each class, taken in order
of a hash of doc_id; that bound is the only sample. Training documents are seen
whole as well, a block of chunks at a time.

Edge cases: a null or empty text is one chunk of padding and has a score; a
label that is null teaches nothing; with labels of one class or none the score
is the share of 1 among them, or 0.5; equal texts have equal scores; a document
with several labels counts once for each in fitting.
"""

from __future__ import annotations

import ctypes
import os
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rankloom.llm.words import give_back, row_chunks, text_buffers, tidy

CHUNK, STEP, WIDTH, WIDE, FILTERS, BLOCK = 512, 4, 8, 4, 16, 2048


_SET: set[int] = set()


def one_thread_each() -> None:
    """Keeps numpy's matrix products, which are small here, on the calling thread."""
    if os.getpid() in _SET:
        return
    _SET.add(os.getpid())
    maps = Path("/proc/self/maps")
    found = {line.split()[-1] for line in maps.read_text().splitlines() if "openblas" in line} if maps.exists() else ()
    for path in found:
        library = ctypes.CDLL(path)
        for name in ("scipy_openblas_set_num_threads64_", "scipy_openblas_set_num_threads", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)


def padded_chunks(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(chunks x CHUNK bytes with zeros behind each text, first chunk of each document)."""
    length = np.diff(offsets)
    chunks = np.maximum(1, -(-length // CHUNK))
    first = np.concatenate([[0], np.cumsum(chunks)])
    out = np.zeros(first[-1] * CHUNK, np.uint8)
    if len(length) == 1:
        out[: length[0]] = data[offsets[0] : offsets[1]]
        return out.reshape(-1, CHUNK), first
    shift = first[:-1] * CHUNK - offsets[:-1]
    out[np.arange(offsets[0], offsets[-1]) + np.repeat(shift, length)] = data[offsets[0] : offsets[-1]]
    return out.reshape(-1, CHUNK), first


def pooled(model: dict[str, np.ndarray], chunks: np.ndarray, last: np.ndarray, where: bool = False):
    """Largest filter response of each chunk (and its window); windows end in the next chunk unless it is a text's last."""
    n = len(chunks)
    steps = CHUNK // STEP
    cells = model["bytes"][chunks.reshape(-1)].reshape(n * steps, STEP * WIDE)
    half = STEP * WIDE
    left, right = cells @ model["filters"][:half], cells @ model["filters"][half:]
    response = left.reshape(n, steps, FILTERS)
    right = right.reshape(n, steps, FILTERS)
    response[:, :-1] += right[:, 1:]
    follows = np.flatnonzero(~last)
    response[follows, -1] += right[follows + 1, 0]
    response[last, -1] += model["blank"]
    if where:
        best = response.argmax(1)
        return np.take_along_axis(response, best[:, None], 1)[:, 0], best
    return response.max(1)


def document_features(peaks: np.ndarray, first: np.ndarray, bias: np.ndarray) -> np.ndarray:
    active = np.maximum(peaks + bias, 0)
    most = np.maximum.reduceat(active, first[:-1], axis=0)
    mean = np.add.reduceat(active, first[:-1], axis=0) / np.diff(first)[:, None]
    return np.concatenate([most, mean], 1)


def with_blank(model: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Adds the response of the second half of a filter to padding."""
    half = STEP * WIDE
    return model | {"blank": np.tile(model["bytes"][0], STEP) @ model["filters"][half:]}


def probability(model: dict[str, np.ndarray], data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """P(label 1) of some texts."""
    one_thread_each()
    if "prior" in model:
        return np.full(len(offsets) - 1, float(model["prior"]))
    out = []
    for lo, hi in row_chunks(offsets, 1 << 20):
        part = offsets[lo : hi + 1]
        chunks, first = padded_chunks(data, part)
        last = ends_of_texts(first)
        peaks = np.concatenate([_block(model, chunks, last, a) for a in range(0, len(chunks), BLOCK)])
        z = document_features(peaks, first, model["bias"]) @ model["out"] + model["out_bias"]
        out.append(1 / (1 + np.exp(-z.astype(np.float64))))
    return np.concatenate(out) if out else np.zeros(0)


def ends_of_texts(first: np.ndarray) -> np.ndarray:
    last = np.zeros(first[-1], bool)
    last[first[1:] - 1] = True
    return last


def _block(model: dict[str, np.ndarray], chunks: np.ndarray, last: np.ndarray, a: int, where: bool = False):
    """pooled() of BLOCK chunks from a on, with one more in sight, so that memory is bounded for any text."""
    b = min(len(chunks), a + BLOCK)
    seen = last[a : b + 1].copy()
    seen[-1] = True
    found = pooled(model, chunks[a : b + 1], seen, where)
    return (found[0][: b - a], found[1][: b - a]) if where else found[: b - a]


def fit(texts: list[bytes], labels: np.ndarray, epochs: int = 24, seed: int = 7, batch: int = 32) -> dict[str, np.ndarray]:
    """A model from texts and 0/1 labels; both classes weigh the same."""
    if len(set(labels.tolist())) < 2:
        return {"prior": np.array(labels.mean() if len(labels) else 0.5)}
    one_thread_each()
    rng = np.random.default_rng(seed)
    half = STEP * WIDE
    m = {
        "bytes": rng.normal(0, 0.5, (256, WIDE)),
        "filters": rng.normal(0, 0.3, (2 * half, FILTERS)),
        "bias": np.zeros(FILTERS),
        "out": rng.normal(0, 0.3, 2 * FILTERS),
        "out_bias": np.zeros(()),
    }
    m = {k: v.astype(np.float32) for k, v in m.items()}
    moments = {k: [np.zeros_like(v), np.zeros_like(v)] for k, v in m.items()}
    weight = np.where(labels == 1, 0.5 / labels.mean(), 0.5 / (1 - labels.mean()))
    t = 0
    for epoch in range(epochs):
        order = rng.permutation(len(texts))
        for b in range(0, len(order), batch):
            ids = order[b : b + batch]
            data = np.frombuffer(b"".join(texts[i] for i in ids), np.uint8)
            offsets = np.concatenate([[0], np.cumsum([len(texts[i]) for i in ids])])
            grads = _gradients(with_blank(m), data, offsets, labels[ids], weight[ids])
            t += 1
            rate = 0.01 * (1 - epoch / epochs) + 0.001
            for k, g in grads.items():
                a, v = moments[k]
                a *= 0.9
                a += 0.1 * g
                v *= 0.99
                v += 0.01 * g * g
                m[k] -= (rate * (a / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)).astype(np.float32)
    return with_blank(m)


def _gradients(m: dict, data: np.ndarray, offsets: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict:
    """Of the weighted logistic loss, through pooling back to filters and byte vectors."""
    chunks, first = padded_chunks(data, offsets)
    last = ends_of_texts(first)
    blocks = [_block(m, chunks, last, a, True) for a in range(0, len(chunks), BLOCK)]
    peaks, best = (np.concatenate(x) for x in zip(*blocks, strict=True))
    feats = document_features(peaks, first, m["bias"])
    p = 1 / (1 + np.exp(-(feats @ m["out"] + m["out_bias"])))
    dz = ((p - y) * weight / len(y)).astype(np.float32)
    grads = {"out": feats.T @ dz + 1e-4 * m["out"], "out_bias": dz.sum()}
    dfeat = dz[:, None] * m["out"][None]
    doc = np.repeat(np.arange(len(y)), np.diff(first))
    active = np.maximum(peaks + m["bias"], 0)
    top = feats[:, :FILTERS][doc]
    dact = dfeat[:, FILTERS:][doc] / np.diff(first)[doc][:, None] + dfeat[:, :FILTERS][doc] * (active == top)
    dpeak = dact * (active > 0)
    grads["bias"] = dpeak.sum(0)
    flat = np.concatenate([chunks.reshape(-1), np.zeros(WIDTH, np.uint8)])
    grads["filters"], grads["bytes"] = np.zeros_like(m["filters"]), np.zeros_like(m["bytes"])
    for a in range(0, len(chunks), BLOCK):
        here, part = best[a : a + BLOCK], dpeak[a : a + BLOCK]
        start = ((a + np.arange(len(here)))[:, None] * CHUNK + here * STEP).reshape(-1)
        take = flat[start[:, None] + np.arange(WIDTH)]
        beyond = (last[a : a + BLOCK, None] & (here == CHUNK // STEP - 1)).reshape(-1)
        take[beyond, STEP:] = 0
        inputs = m["bytes"][take].reshape(len(here), FILTERS, WIDTH * WIDE)
        grads["filters"] += np.einsum("cfw,cf->wf", inputs, part)
        back = part[:, :, None] * m["filters"].T[None]
        np.add.at(grads["bytes"], take.reshape(-1), back.reshape(-1, WIDE))
    return grads


def may_learn(doc_id: Column) -> Column:
    """Rows whose label may be seen: crc32 of doc_id as text, mod 3, is not 1."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 3 != 1


def fitted(docs: DataFrame, labels: DataFrame, per_class: int = 1500, seed: int = 7) -> dict[str, np.ndarray]:
    """The model from per_class labelled rows of each class at most."""
    known = labels.filter(may_learn(F.col("doc_id"))).select("doc_id", "quality")
    picks = [known.filter(F.col("quality") == c).orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(per_class) for c in (0, 1)]
    picked = picks[0].unionByName(picks[1])
    table = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").select("quality", F.coalesce("text", F.lit("")).cast("binary").alias("text"), F.xxhash64("doc_id").alias("o")).toArrow()
    table = table.sort_by([("o", "ascending"), ("text", "ascending")])
    model = fit(table["text"].to_pylist(), np.array(table["quality"].to_pylist(), np.int64), seed=seed)
    del table
    give_back()
    return model


def score_documents(docs: DataFrame, model: dict[str, np.ndarray], name: str = "score") -> DataFrame:
    """docs with a column name: the score of the whole text of every row."""
    schema = T.StructType([*docs.schema.fields, T.StructField(name, T.DoubleType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = text_buffers(batch.column(batch.schema.get_field_index("text")))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(probability(model, data, offsets))], names=[*batch.schema.names, name])

    return docs.mapInArrow(tidy(run), schema)


def classify_quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """op9: doc_id, held_out, score, predicted."""
    scored = score_documents(docs.select("doc_id", "text"), fitted(docs, labels))
    held = F.coalesce(~may_learn(F.col("doc_id")), F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"))


def quality_stage(docs: DataFrame, labels: DataFrame, reject_below: float = 0.5) -> DataFrame:
    """documents -> documents that score reject_below or more."""
    name = "_score"
    while name in docs.columns:
        name += "_"
    return score_documents(docs, fitted(docs, labels), name).filter(F.col(name) >= reject_below).drop(name)
