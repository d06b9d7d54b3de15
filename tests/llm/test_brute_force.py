"""Operators against plain Python over the smallest tables and planted cases."""

import collections
import hashlib
import math
import re
import zlib

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from rankloom.llm import queries as q
from rankloom.llm.common import load

LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))


@pytest.fixture(scope="module")
def documents(spark, tiny):
    return {r.doc_id: r.text for r in load(spark, tiny, "documents", "doc_id", "text").collect()}


def brute_components(texts, width, percent):
    sets = {}
    for d, t in texts.items():
        w = words(t)
        sets[d] = frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])
    root = {d: d for d in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(texts)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, r = find(a), find(b)
                root[max(p, r)] = min(p, r)
    return {d: (len(sets[d]), find(d)) for d in texts}


def test_jaccard_components(spark, tiny, documents):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in q.op3_jaccard(spark, tiny).collect()}
    assert got == brute_components(documents, 4, 85)


def test_jaccard_chains_near_threshold(spark):
    """Copies that drift word by word link in a chain, though its ends are unlike."""
    base = [f"w{i}" for i in range(60)]
    texts, current = {}, list(base)
    for i in range(25):
        texts[i] = " ".join(current)
        current[(7 * i) % 60] = f"x{i}"
    texts |= {100 + i: " ".join(f"p{j}" for j in range(40)) + " " + " ".join(f"y{i}_{j}" for j in range(30)) for i in range(30)}
    texts |= {200: "a b", 201: "A b", 202: "a  b c", 203: "", 204: None, 205: "  \n", 206: "A B C D", 207: "a b c d"}
    from rankloom.llm.jaccard import jaccard_components

    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_components(docs).collect()}
    assert got == brute_components(texts, 4, 85)


def test_simhash_contract(spark, tiny, documents):
    got = {r.doc_id: r for r in q.op2_simhash(spark, tiny).collect()}
    ids = sorted(documents)
    prints = {r.doc_id: int(r.fingerprint, 16) for r in got.values()}
    by_text = collections.defaultdict(set)
    for i, d in enumerate(ids):
        text, nxt = documents[d], documents[ids[(i + 1) % len(ids)]]
        k = len(text) // 4
        edited = text[: len(text) - k] + nxt[:k]
        r = got[d]
        assert r.n_chars == len(text) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        other = prints[ids[(i + 1) % len(ids)]]
        assert r.near_next == 1 - bin(prints[d] ^ other).count("1") / 64
        assert r.near_edited == 1 - bin(prints[d] ^ int(r.edited_fingerprint, 16)).count("1") / 64
        by_text[text].add(prints[d])
        if d % 20 == 0:
            assert r.n_within == sum(bin(prints[d] ^ p).count("1") <= 3 for p in prints.values())
    assert all(len(v) == 1 for v in by_text.values())
    assert sum(r.near_edited for r in got.values()) / len(got) > sum(r.near_next for r in got.values()) / len(got) + 0.15


def test_simhash_over_several_buckets(spark):
    from rankloom.llm.simhash import fingerprint_edits, with_next

    docs = spark.range(500).select((F.col("id") * 3).alias("doc_id"), F.concat(F.lit("text number "), F.col("id")).alias("text"))
    rows = {r.doc_id: r.next_text for r in with_next(docs, rows_each=7).collect()}
    assert rows == {3 * i: f"text number {(i + 1) % 500}" for i in range(500)}
    assert fingerprint_edits(docs).count() == 500


def test_radius_search_is_exact(spark):
    import random

    from rankloom.llm.simhash import within_radius

    random.seed(4)
    centre = [random.getrandbits(63) for _ in range(20)]
    prints = [c ^ sum(1 << b for b in random.sample(range(63), k)) for c in centre for k in range(6)]
    df = spark.createDataFrame([(p,) for p in prints], "fp long")
    got = {(r.q, r.d) for r in within_radius(df, df).collect()}
    assert got == {(a, b) for a in prints for b in prints if bin(a ^ b).count("1") <= 3}


def test_mix_against_sql(spark, tiny):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{tiny}/documents.parquet'")
    want = c.execute(q.oracle_sql()["op1_mix"]).fetchall()
    got = [tuple(r) for r in q.op1_mix(spark, tiny).collect()]
    assert sorted(got) == sorted(want)


def test_water_filling(spark):
    from rankloom.llm.mixing import share_among_children

    rows = [("a", 100, 1, 90), ("b", 10, 1, 90), ("c", 100, 2, 90), ("d", 5, 0, 90)]
    df = spark.createDataFrame(rows, "name string, supply long, weight long, budget long")
    got = {r["name"]: r["grant"] for r in share_among_children(df, []).collect()}
    assert got["b"] == 10 and got["d"] == 0 and got["a"] + got["c"] == 80 and abs(got["c"] - 53) <= 1
    short = {r["name"]: r["grant"] for r in share_among_children(df.withColumn("budget", F.lit(1000).cast("long")), []).collect()}
    assert short == {"a": 100, "b": 10, "c": 100, "d": 0}


def test_shards(spark, tiny, documents):
    rows = q.op6_shards(spark, tiny).collect()
    by = collections.defaultdict(list)
    for r in rows:
        text = documents[r.doc_id]
        assert r["size"] == len(text.encode()) + 1 and r.text_crc32 == zlib.crc32(text.encode()) and r.law == "rows"
        by[r.shard].append(r.slot)
    assert set(by) == set(range(16)) and all(sorted(s) == list(range(len(s))) for s in by.values())
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1
    homes = collections.defaultdict(set)
    for r in rows:
        homes[documents[r.doc_id]].add(r.shard)
    assert all(len(s) == 1 for s in homes.values())


def test_shards_with_a_group_of_a_third(spark):
    from rankloom.llm.sharding import shard_documents

    docs = spark.range(960).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, F.lit("same")).otherwise(F.col("id").cast("string")).alias("text"))
    rows = shard_documents(docs).collect()
    counts = collections.Counter(r.shard for r in rows)
    assert set(counts.values()) == {60} and len({(r.shard, r.slot) for r in rows}) == 960
    assert collections.Counter(r.shard for r in rows if r.linked).most_common(1)[0][1] == 60


def test_shards_of_large_groups_and_of_copies_only(spark):
    from rankloom.llm.sharding import granted_moves, shard_documents

    third = F.when(F.col("id") % 3 == 0, F.lit("same")).otherwise((F.col("id") % 320).cast("string"))
    rows = shard_documents(spark.range(960).select((F.col("id") % 3 == 0).cast("long").alias("doc_id"), third.alias("text"))).collect()
    assert sorted(collections.Counter(r.shard for r in rows if r.doc_id == 1).values()) == [20, 60, 60, 60, 60, 60]
    rows = shard_documents(spark.range(960).select((F.col("id") % 240).alias("doc_id"), (F.col("id") % 240).cast("string").alias("text"))).collect()
    homes = collections.defaultdict(set)
    for r in rows:
        homes[r.doc_id].add(r.shard)
    assert set(collections.Counter(r.shard for r in rows).values()) == {60}
    assert sum(len(h) > 1 for h in homes.values()) < 80
    assert granted_moves({(0, 1): 10, (1, 0): 7}, [20, 20], [20, 20]) == {(0, 1): 7, (1, 0): 7}
    asked = {(0, 1): 9, (1, 2): 9, (2, 1): 5, (2, 0): 1}
    granted = granted_moves(asked, [9, 9, 9], [9, 9, 9])
    moved = lambda s: sum(c * ((j == s) - (i == s)) for (i, j), c in granted.items())
    assert all(granted[k] <= asked[k] for k in asked) and all(moved(s) == 0 for s in range(3)) and granted[1, 2] >= 5


def test_chat_against_sql(spark, tiny):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW conversations AS SELECT * FROM '{tiny}/conversations.parquet'")
    want = c.execute(q.oracle_sql()["op4_chat"]).fetchall()
    assert sorted(tuple(r) for r in q.op4_chat(spark, tiny).collect()) == sorted(want)


def test_lm_against_plain_backoff(spark, tiny, documents):
    got = {r.doc_id: r for r in q.op8_lm(spark, tiny).collect()}
    end, other = "\0end", "\0other"
    tokens = {d: words(t) + [end] for d, t in documents.items()}
    held = {d: zlib.crc32(str(d).encode()) % 10 == 0 for d in documents}
    counts = collections.Counter(w for d, ws in tokens.items() if not held[d] for w in ws)
    n, v = sum(counts.values()), len(counts)
    head = {w for w in counts if w != end}
    p1 = lambda w: (counts[w] + 0.1) / (n + 0.1 * (v + 1))
    rest = 1 - sum(p1(w) for w in head | {end})
    kind = lambda w: w if w in head or w == end else other
    grams = collections.defaultdict(collections.Counter)
    for d, ws in tokens.items():
        for i, w in enumerate(ws):
            for k in (1, 2):
                if not held[d] and i >= k and all(x in head for x in ws[i - k : i]):
                    grams[tuple(ws[i - k : i])][kind(w)] += 1

    def p(context, x):
        if not context:
            return rest if x == other else p1(x)
        below = p(context[1:], x)
        seen = grams.get(context)
        return (seen.get(x, 0) + len(seen) * below) / (sum(seen.values()) + len(seen)) if seen else below

    for d, ws in tokens.items():
        total = 0.0
        for i, w in enumerate(ws):
            k = 2
            while k and (i < k or not all(x in head for x in ws[i - k : i])):
                k -= 1
            x = kind(w)
            total += math.log10(p(tuple(ws[i - k : i]), x) * (p1(w) / rest if x == other else 1))
        r = got[d]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(ws), sum(counts[w] > 0 for w in ws), n, held[d])
        assert r.base_score == pytest.approx(sum(math.log10(p1(w)) for w in ws), rel=1e-9)
        assert r.score == pytest.approx(total, rel=1e-9)


def test_lm_long_texts_enter_in_pieces(spark):
    from rankloom.llm.lm import score_texts

    docs = [(i, "the cat sat on the mat " * (1 + 400 * (i == 3))) for i in range(12)]
    rows = {r.doc_id: r for r in score_texts(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert rows[3].n_tokens == 401 * 6 + 1 and rows[3].score > rows[3].base_score


def test_lm_keeps_rare_contexts(spark):
    """A phrase of rare words, repeated among many other tokens, is known, to the last digit of plain counting."""
    from rankloom.llm.lm import held_out, score_texts

    docs = [(i, " ".join(f"w{i}x{j}" for j in range(400))) for i in range(60)]
    docs += [(i, "quick amber foxes") for i in range(60, 63)] + [(i, "foxes amber quick") for i in range(63, 66)]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    held = {r.doc_id for r in df.filter(held_out(F.col("doc_id"))).collect()}
    counts = collections.Counter(w for i, t in docs if i not in held for w in [*t.split(), ""])
    grams = collections.defaultdict(collections.Counter)
    for i, t in docs:
        ws = [*t.split(), ""]
        for at in range(len(ws)):
            for k in (1, 2):
                if at >= k and i not in held:
                    grams[tuple(ws[at - k : at])][ws[at]] += 1
    floor = sum(counts.values()) + 0.1 * (len(counts) + 1)

    def p(context, x):
        below = p(context[1:], x) if context else 0
        seen = grams.get(context)
        if not context:
            return (counts[x] + 0.1) / floor
        return (seen[x] + len(seen) * below) / (sum(seen.values()) + len(seen)) if seen else below

    for r in score_texts(df).collect():
        ws = [*docs[r.doc_id][1].split(), ""]
        assert r.score == pytest.approx(sum(math.log10(p(tuple(ws[max(0, i - 2) : i]), w)) for i, w in enumerate(ws)), rel=1e-9)


def test_leaks_are_found_and_clean_texts_left(spark, tiny, documents):
    items = {r.item_id: r.text for r in load(spark, tiny, "benchmark").collect()}
    want = {(d, i) for d, t in documents.items() for i, x in items.items() if x in t}
    got = {(r.doc_id, r.item_id) for r in q.op5_decontaminate(spark, tiny).collect()}
    assert want <= got
    five = lambda t: {tuple(w[i : i + 5]) for w in [re.findall(r"\w+", t.lower())] for i in range(len(w) - 4)}
    for d, i in got - want:
        assert len(five(documents[d]) & five(items[i])) >= 0.5 * len(five(items[i]))


def test_leaks_in_planted_texts(spark):
    from rankloom.llm.decontaminate import decontaminate_stage, find_leaks

    filler = " ".join(f"word{i} the of and" for i in range(400))
    item = "What colour is the ninth gate of the old mill? It was painted green by the third miller of Arn."
    bench = spark.createDataFrame([(1, item), (2, "tiny"), (3, None), (4, item)], "item_id long, text string")
    docs = [(1, filler + " " + item + " " + filler), (2, filler), (3, item.upper().replace(" ", "\n")), (4, ""), (5, None), (6, "What colour is the ninth gate of the old mill?"), (7, item[:40])]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    found = find_leaks(df, bench).collect()
    assert {(r.doc_id, r.item_id) for r in found} == {(1, 1), (1, 4), (3, 1), (3, 4)}
    assert {r.doc_id for r in decontaminate_stage(df, bench).collect()} == {2, 4, 5, 6, 7}


def test_leaks_with_a_word_edited_in_a_short_answer(spark):
    from rankloom.llm.decontaminate import find_leaks

    question = "Which colour did the keepers paint upon the ninth gate of the old mill beyond the northern river?"
    answers = ["bright blue", "a rather deep and stormy blue", "grey then green then blue over old white lime"]
    edited = ["bright teal", "a rather pale and stormy blue", "grey then green then red over old white lime"]
    bench = spark.createDataFrame([(i, f"{question} {a}") for i, a in enumerate(answers)], "item_id long, text string")
    for i, a in enumerate(edited):
        found = find_leaks(spark.createDataFrame([(i, f"Some words before. {question} {a} and some behind.")], "doc_id long, text string"), bench).collect()
        assert i in {r.item_id for r in found}, a
    far = f"Some words before. {question} " + "and so it went on " * 40 + "bright grey old lime"
    assert find_leaks(spark.createDataFrame([(1, far)], "doc_id long, text string"), bench.filter("item_id = 0")).collect() == []


def test_leaks_of_items_without_id_and_of_short_items(spark):
    from rankloom.llm.decontaminate import decontaminate_stage, find_leaks

    item = "What stands behind the ninth gate of the old mill? A copper bell from the lost harbour tower"
    bench = spark.createDataFrame([(None, item), (2, "Purple Narwhal!"), (3, "purple"), (None, None), (5, " ")], "item_id long, text string")
    docs = spark.createDataFrame([(1, f"so {item} it is"), (2, "a purple, narwhal swam"), (3, "narwhal purple"), (4, "a purple"), (5, "narwhal"), (6, None)], "doc_id long, text string")
    found = {(r.doc_id, r.item_id) for r in find_leaks(docs, bench).collect()}
    assert found == {(1, None), (2, 2), (2, 3), (3, 3), (4, 3)}
    assert [r.doc_id for r in decontaminate_stage(docs, bench).orderBy("doc_id").collect()] == [5, 6]


def test_leaks_do_not_depend_on_slices(spark, tiny, monkeypatch):
    from rankloom.llm import decontaminate as m

    bench = load(spark, tiny, "benchmark")
    rows = [(r.item_id, r.text[: len(r.text) * 2 // 3]) for r in bench.collect()]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = lambda: {(r.doc_id, r.item_id): r.score for r in m.find_leaks(docs, bench, threshold=0.5, overlap=0.0).collect()}
    one = found()
    monkeypatch.setattr(m, "SLICE", -(-bench.count() // 2))
    assert one and found() == pytest.approx(one, rel=1e-9)


def test_block_max_equals_scoring_all(spark, tiny, documents):
    """Block-max bounds open every block that holds an item at the threshold."""
    import numpy as np
    import pyarrow as pa

    from rankloom.llm.decontaminate import BLOCK_ITEMS, ItemIndex
    from rankloom.llm.words import word_chunks

    items = [(r.item_id, r.text) for r in load(spark, tiny, "benchmark").collect()]
    index = ItemIndex(items, 0.2, 5)
    texts = pa.array(list(documents.values()))
    for _, _, chunk in word_chunks(texts, alnum=True):
        got = {(d, i): s for d, i, s in index.retrieve(chunk)}
        want = {}
        for d in range(chunk.docs):
            h = chunk.hashes[chunk.first[d] : chunk.first[d + 1]]
            for a in range(0, max(1, len(h)), index.stride):
                passage = set(h[a : a + 2 * index.stride].tolist())
                terms = [i for i, t in enumerate(index.terms) if int(t) in passage]
                rows = np.isin(index.post_term, terms)
                scores = np.bincount(index.post_item[rows], index.post_weight[rows], minlength=index.blocks * BLOCK_ITEMS)
                for i in np.flatnonzero(scores >= 0.2):
                    want[d, int(i)] = max(want.get((d, int(i)), 0), scores[i])
        assert got.keys() == want.keys() and all(got[k] == pytest.approx(want[k]) for k in got)


def test_language_held_out(spark, small):
    truth = {r.doc_id: (r.lang, r.text) for r in load(spark, small, "documents", "doc_id", "lang", "text").collect()}
    rows = q.op7_language(spark, small).collect()
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) and 0 <= r.score <= 1 for r in rows)
    assert sum(r.lang_pred == truth[r.doc_id][0] for r in held) / len(held) > 0.98


def test_language_mixtures(spark):
    from rankloom.llm.language import fitted, identify

    en, de = "the quick brown fox jumps over the lazy dog and the cat ", "der schnelle braune fuchs springt ueber den faulen hund und die katze "
    learn = spark.createDataFrame([(i, en * 3 if i % 2 else de * 3, "en" if i % 2 else "de") for i in range(40)], "doc_id long, text string, lang string")
    names, table = fitted(learn)
    docs = [(1, en * 5), (2, de * 5), (3, (en + de) * 6), (4, "12 34 ..."), (5, None), (6, "")]
    got = {r.doc_id: r for r in identify(spark.createDataFrame(docs, "doc_id long, text string"), names, table).collect()}
    assert got[1].lang_set == "en" and got[2].lang_set == "de" and set(got[3].lang_set.split("+")) == {"en", "de"}
    assert {got[i].lang_pred for i in (4, 5, 6)} == {"und"} and got[3].score < 0.8


def test_quality_held_out(spark, small):
    truth = {r.doc_id: r.quality for r in load(spark, small, "labels").collect()}
    rows = q.op9_quality(spark, small).collect()
    held = [r for r in rows if r.held_out and r.doc_id in truth]
    assert sum(r.predicted == truth[r.doc_id] for r in held) / len(held) > 0.95
    assert all(r.predicted == (r.score >= 0.5) for r in rows)


def test_network_learns_from_every_chunk(monkeypatch):
    import numpy as np

    from rankloom.llm import quality as m

    rng = np.random.default_rng(5)
    labels = np.arange(40) % 2
    texts = [rng.integers(97, 123, 60 * m.CHUNK, dtype=np.uint8).tobytes() for _ in labels]
    model = m.fit(texts, labels, epochs=1)
    marked = [t[: m.CHUNK] + b"ZQ" * (m.CHUNK // 2) + t[2 * m.CHUNK :] if y else t for t, y in zip(texts, labels, strict=True)]
    assert not np.array_equal(model["bytes"][ord("Z")], m.fit(marked, labels, epochs=1)["bytes"][ord("Z")])
    data, offsets = np.frombuffer(b"".join(marked), np.uint8), np.cumsum([0, *map(len, marked)])
    whole = m._gradients(model, data, offsets, labels, np.ones(40))
    monkeypatch.setattr(m, "BLOCK", 7)
    parts = m._gradients(model, data, offsets, labels, np.ones(40))
    assert all(np.allclose(whole[k], parts[k], rtol=1e-3, atol=1e-5) for k in whole)


def test_network_gradients():
    """Backward pass against differences."""
    import numpy as np

    from rankloom.llm import quality as m

    rng = np.random.default_rng(3)
    model = {"bytes": rng.normal(0, 0.5, (256, m.WIDE)), "filters": rng.normal(0, 0.3, (m.WIDTH * m.WIDE, m.FILTERS)), "bias": rng.normal(0, 0.1, m.FILTERS), "out": rng.normal(0, 0.3, 2 * m.FILTERS), "out_bias": np.array(0.1)}
    texts = [bytes(rng.integers(1, 250, n, dtype=np.uint8)) for n in (40, 700, 1300)]
    data, offsets = np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)])
    y, weight = np.array([0, 1, 1]), np.ones(3)

    def loss(p):
        z = []
        for i in range(3):
            z.append(m.probability(m.with_blank(p), data[offsets[i] : offsets[i + 1]], np.array([0, offsets[i + 1] - offsets[i]]))[0])
        z = np.array(z)
        return -(y * np.log(z) + (1 - y) * np.log(1 - z)).mean() + 0.5e-4 * (p["out"] ** 2).sum()

    grads = m._gradients(m.with_blank(model), data, offsets, y, weight)
    for name, at in (("out", 3), ("bias", 2), ("filters", (9, 4)), ("filters", (20, 1)), ("bytes", (int(data[5]), 1))):
        h = 1e-4
        up, down = ({k: v.astype(float).copy() for k, v in model.items()} for _ in range(2))
        up[name][at] += h
        down[name][at] -= h
        assert grads[name][at] == pytest.approx((loss(up) - loss(down)) / (2 * h), rel=0.05, abs=1e-4)


def test_pipeline_stages(spark, tiny, documents):
    import corpus_pipeline
    from rankloom.llm import pipeline

    docs = load(spark, tiny, "documents")
    kept = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id for r in docs.select("doc_id").collect()}
        docs = pipeline.written(stage(spark, docs, tiny), name)
        assert docs.columns == load(spark, tiny, "documents").columns
        kept[name] = {r.doc_id for r in docs.select("doc_id").collect()}
        assert kept[name] <= before
    quality = {r.doc_id: r.quality for r in load(spark, tiny, "labels").collect()}
    good = [d for d, x in quality.items() if x == 1]
    assert sum(d in kept["quality"] for d in good) >= 0.95 * len(good)
    want = brute_components({d: documents[d] for d in kept["quality"]}, 5, 80)
    assert kept["near_duplicates"] == {d for d, (_, c) in want.items() if c == d}
    items = [r.text for r in load(spark, tiny, "benchmark").collect()]
    assert not [d for d in kept["decontamination"] if any(x in documents[d] for x in items)]
    out = corpus_pipeline.STAGES[-1][1](spark, docs, tiny).collect()
    assert len(out) == docs.count() and len({(r.shard, r.slot) for r in out}) == len(out)


def test_jaccard_of_one_large_group_of_near_copies(spark, monkeypatch):
    """2,000 texts around the threshold: the links of all pairs, without naming the pairs within the group."""
    from rankloom.llm import jaccard

    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in rng.integers(0, 10_000, 80)]
    texts = []
    for i in range(2000):
        text = list(base)
        for at in rng.integers(0, 80, rng.integers(1, 4)):
            text[at] = f"x{rng.integers(0, 40)}"
        texts.append((i, " ".join(text)))
    docs = spark.createDataFrame(texts, "doc_id bigint, text string")
    counted = []
    written = jaccard.Scratch.written
    monkeypatch.setattr(jaccard.Scratch, "written", lambda self, df, label: (out := written(self, df, label), counted.append(out.count()) if label == "queries" else None)[0])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.jaccard_components(docs).collect()}
    assert sum(counted) < 20 * len(texts)
    sets = [{tuple(w[k : k + 4]) for k in range(len(w) - 3)} for w in (t.split() for _, t in texts)]
    held = {}
    for i, s in enumerate(sets):
        for shingle in s:
            held.setdefault(shingle, []).append(i)
    common = np.zeros((len(texts), len(texts)), np.int32)
    for ids in held.values():
        common[np.ix_(ids, ids)] += 1
    size = np.array([len(s) for s in sets])
    linked = 100 * common >= 85 * (size[:, None] + size[None, :] - common)
    want = np.arange(len(texts))
    while True:
        new = np.array([want[row].min() for row in linked])
        if (new == want).all():
            break
        want = new
    assert got == {i: (int(size[i]), int(want[i])) for i in range(len(texts))}


def test_mix_of_repeated_rows(spark, tiny):
    """Every row three times: the takes of a repeated document add up to the grant, as in SQL."""
    from rankloom.llm.mixing import mix_documents

    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT d.* FROM '{tiny}/documents.parquet' d, range(3)")
    want = c.execute(q.oracle_sql()["op1_mix"]).fetchall()
    docs = load(spark, tiny, "documents")
    got = [tuple(r) for r in mix_documents(docs.unionByName(docs).unionByName(docs)).collect()]
    assert sorted(got) == sorted(want)


def test_chat_of_named_and_unnamed_conversations(spark):
    """A row without id never stands for a conversation that has one."""
    from rankloom.llm.chat import format_chats

    rows = [(3, 0, "user", "hi"), (None, 0, "user", "hi"), (None, 4, "user", "hi"), (None, 1, "user", "alone"), (None, 1, "user", "alone"), (5, 0, "user", "a"), (5, 1, "user", "b"), (None, 0, "user", "a")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = [tuple(r) for r in format_chats(df).collect()]
    assert {r[:3] for r in got} == {(3, 1, 3), (None, 1, 2), (5, 2, 1)}
    c = duckdb.connect()
    c.register("conversations", df.toPandas().astype({"conv_id": "Int64"}))
    assert sorted(got, key=str) == sorted(c.execute(q.oracle_sql()["op4_chat"]).fetchall(), key=str)


def test_lm_spreads_common_contexts(spark, tiny, monkeypatch):
    """Contexts in many parts are counted as in one."""
    from rankloom.llm import lm

    docs = load(spark, tiny, "documents")
    want = {r.doc_id: r.score for r in lm.score_texts(docs).collect()}
    monkeypatch.setattr(lm, "COMMON", 8)
    monkeypatch.setattr(lm, "BLOCK_BYTES", 1 << 15)
    got = {r.doc_id: r.score for r in lm.score_texts(docs).collect()}
    assert got == pytest.approx(want, rel=1e-9)


def test_radius_search_of_many_blocks(spark):
    """More blocks, as for more numbers, find the same pairs."""
    from rankloom.llm.simhash import blocks_for, within_radius

    rng = np.random.default_rng(3)
    prints = []
    for base in rng.integers(-(2**63), 2**63 - 1, 20):
        for flips in range(6):
            x = int(base) % 2**64
            for bit in rng.choice(64, flips, replace=False):
                x ^= 1 << int(bit)
            prints.append(x - 2**64 if x >= 2**63 else x)
    df = spark.createDataFrame([(p,) for p in set(prints)], "fp long")
    want = {(a, b) for a in prints for b in prints if bin((a ^ b) % 2**64).count("1") <= 3}
    for blocks in (5, 6, 8):
        assert {(r.q, r.d) for r in within_radius(df, df, 3, blocks).collect()} == want
    assert [blocks_for(n, 3) for n in (0, 10**7, 10**9, 10**12)] == [5, 5, 6, 8]


def test_leaks_of_repeated_and_empty_items(spark):
    from rankloom.llm.decontaminate import find_leaks

    text = "What is the name of the largest moon of the ringed planet? It is called Titan by all."
    bench = spark.createDataFrame([(1, text), (1, None), (None, None), (1, text), (2, "")], "item_id long, text string")
    docs = spark.createDataFrame([(7, "before " + text + " after"), (8, "nothing here"), (9, None)], "doc_id long, text string")
    assert [(r.doc_id, r.item_id) for r in find_leaks(docs, bench).collect()] == [(7, 1), (7, 1)]


def test_leaks_in_a_very_long_text(monkeypatch):
    """Passages are searched some at a time, with the same result."""
    import pyarrow as pa

    from rankloom.llm import decontaminate as m

    rng = np.random.default_rng(0)
    items = [(i, " ".join(f"w{x}" for x in rng.zipf(1.3, 30) % 5000)) for i in range(300)]
    text = " ".join(f"w{x}" for x in rng.zipf(1.3, 60_000) % 5000)
    text = pa.array([text + " " + items[5][1] + " " + text[:1000] + items[200][1]])
    index = m.ItemIndex(items, 0.4, 5)
    want = sorted(index.leaks(text, 0.5))
    for name, small in (("TERMS_AT_ONCE", 200), ("POSTINGS_AT_ONCE", 500), ("OPEN_AT_ONCE", 7)):
        monkeypatch.setattr(m, name, small)
    assert sorted(index.leaks(text, 0.5)) == want and {5, 200} <= {r[1] for r in want}


def test_language_mixtures_against_plain_em():
    """Proportions by a plain loop over words, languages and rounds, and the same choice of the set."""
    from rankloom.llm.language import choose_languages

    rng = np.random.default_rng(4)
    langs, words = 3, [1, 4, 30, 60, 25]
    owner = np.repeat(np.arange(len(words)), words)
    log_fit = -rng.exponential(1.5, (len(owner), langs))
    for d, lang in enumerate((0, 1, 2, None, 1)):
        mine = np.flatnonzero(owner == d)
        log_fit[mine, lang if lang is not None else rng.integers(0, 2, len(mine))] += 3
    log_fit -= log_fit.max(1, keepdims=True)
    got = choose_languages(np.exp(log_fit), log_fit, owner, len(words))

    def em(rows, allowed):
        part = [1 / len(allowed) if k in allowed else 0.0 for k in range(langs)]
        for _ in range(8):
            share = [0.0] * langs
            for row in rows:
                whole = sum(math.exp(row[k]) * part[k] for k in range(langs))
                for k in range(langs):
                    share[k] += math.exp(row[k]) * part[k] / whole
            part = [x / sum(share) for x in share]
        return part, sum(math.log(sum(math.exp(row[k]) * part[k] for k in range(langs))) for row in rows)

    for d, n in enumerate(words):
        rows = log_fit[owner == d].tolist()
        price = 0.5 * math.log(n + 1) + 3
        allowed = set(range(langs))
        part, likely = em(rows, allowed)
        best, best_part = likely - price * (langs - 1), part
        while len(allowed) > 1:
            allowed = allowed - {min(sorted(allowed), key=lambda k: part[k])}
            if len(allowed) == 1:
                (k,) = allowed
                part, likely = [float(i == k) for i in range(langs)], sum(row[k] for row in rows)
            else:
                part, likely = em(rows, allowed)
            if likely - price * (len(allowed) - 1) >= best:
                best, best_part = likely - price * (len(allowed) - 1), part
        alone = max(range(langs), key=lambda k: sum(row[k] for row in rows))
        if sum(row[alone] for row in rows) >= best:
            best_part = [float(i == alone) for i in range(langs)]
        assert got[d].tolist() == pytest.approx(best_part, abs=1e-9)
    assert (got[3] > 0).sum() == 2


def test_network_against_plain_convolution():
    """Scores by loops over windows, filters and chunks, texts longer than a block of chunks included."""
    from rankloom.llm import quality as m

    rng = np.random.default_rng(2)
    half = m.STEP * m.WIDE
    model = m.with_blank({"bytes": rng.normal(0, 0.5, (256, m.WIDE)), "filters": rng.normal(0, 0.3, (2 * half, m.FILTERS)), "bias": rng.normal(0, 0.1, m.FILTERS), "out": rng.normal(0, 0.3, 2 * m.FILTERS), "out_bias": np.array(0.1)})
    texts = [b"", b"abc", bytes(rng.integers(0, 256, 511, np.uint8)), bytes(rng.integers(0, 256, 512, np.uint8)), bytes(rng.integers(0, 256, 1700, np.uint8))]
    got = m.probability(model, np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)]))
    for text, score in zip(texts, got, strict=True):
        chunks = max(1, -(-len(text) // m.CHUNK))
        padded = np.frombuffer(text.ljust(chunks * m.CHUNK, b"\0") + b"\0" * m.WIDTH, np.uint8)
        pooled = []
        for c in range(chunks):
            windows = [padded[a : a + m.WIDTH] for a in range(c * m.CHUNK, (c + 1) * m.CHUNK, m.STEP)]
            pooled.append([max(float(model["bytes"][w].reshape(-1) @ model["filters"][:, f]) for w in windows) for f in range(m.FILTERS)])
        active = np.maximum(np.array(pooled) + model["bias"], 0)
        z = np.concatenate([active.max(0), active.mean(0)]) @ model["out"] + model["out_bias"]
        assert score == pytest.approx(1 / (1 + math.exp(-z)), rel=1e-6)


def test_pages_against_another_parser(spark, tiny):
    """The words of every page, in order, as a plain reading by the standard library's parser finds them."""
    from html.parser import HTMLParser

    from rankloom.llm.html import INVISIBLE, VOID

    class Plain(HTMLParser):
        def __init__(self):
            super().__init__(convert_charrefs=True)
            self.said, self.hidden = [], []

        def handle_starttag(self, tag, attrs):
            a = dict(attrs)
            gone = tag in INVISIBLE or "hidden" in a or re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", a.get("style") or "")
            if not self.hidden and tag == "img" and a.get("alt"):
                self.said.append(f" {a['alt']} ")
            if tag not in VOID and (self.hidden or gone):
                self.hidden.append(tag)

        def handle_endtag(self, tag):
            if tag in self.hidden:
                while self.hidden.pop() != tag:
                    pass

        def handle_data(self, data):
            if not self.hidden:
                self.said.append(data)

    plain = lambda words: [w for w in words if not re.fullmatch(r"-|\d+\.", w)]
    letters = lambda text: "".join(plain(text.split()))
    pages = {r.page_id: r.html for r in load(spark, tiny, "pages").collect()}
    got = {r.page_id: r.text for r in q.op10_html(spark, tiny).collect()}
    same = 0
    for k, html in pages.items():
        p = Plain()
        p.feed(html or "")
        p.close()
        same += letters(got[k]) == letters(" ".join(p.said))
    assert same == len(pages)


def test_pages_take_linear_time():
    import time

    from rankloom.llm.html import page_text

    for piece in ('<a "', '<a x="', "<script>", "<!", "<i>", "<p><table><i>", "<style>{", "<td rowspan=9>", "<div hidden", "</p>"):
        seconds = []
        for n in (4_000, 16_000):
            begin = time.thread_time()
            page_text(piece * n)
            seconds.append(time.thread_time() - begin)
        assert seconds[1] < 9 * seconds[0] + 0.2, piece


def test_pages_spans_and_style_sheets():
    from rankloom.llm.html import page_text

    assert page_text("<table><tr><td rowspan=2>A<td>B<tr><td>C</table>") == "A  B\n   C"
    assert page_text("<table><tr><td>A<td rowspan=2>B<td>C<tr><td>D<td>E<tr><td>F<td>G</table>") == "A  B  C\nD     E\nF  G"
    assert page_text("<table><tr><td colspan=2>A<td>B<tr><td>C<td>D<td>E</table>") == "A     B\nC  D  E"
    sheet = "<style>/* .p{display:none} */ .x, #q { display : none } p.w{visibility:hidden} @media print { .p { display:none } } b{color:red}</style>"
    assert page_text(sheet + "<p class='a x'>1</p><p id=q>2</p><p class=w>3</p><i class=w>4</i><p class=p>5</p><b>6</b>") == "4\n\n5\n\n6"
    assert page_text("<style>div{display:none} #in{display:block}</style><div>1</div><div id=in>2</div><div style='display:flex'>3</div>") == "2\n3"
    assert page_text("<p title='a > b'>x</p><p title=\"it's\">y") == "x\n\ny"


def test_lm_of_blocks_without_pairs(spark):
    """Texts without words, alone in their blocks, have the end token only."""
    from rankloom.llm.lm import score_texts

    docs = spark.createDataFrame([(i, x) for i, x in enumerate([None, "", " ", "word", "two words", "", "three small words"])], "doc_id long, text string")
    rows = {r.doc_id: r for r in score_texts(docs.repartition(7, "doc_id")).collect()}
    assert len(rows) == 7 and rows[0].n_tokens == rows[5].n_tokens == 1 and rows[0].score == rows[1].score == rows[0].base_score
