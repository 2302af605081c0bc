"""Jaccard groups, vectors, mixing, chat, packing and the pipeline."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from signpart.llm import chat_format, components, jaccard_join, mixing, packing, registry, store, vector_dedup
from tests.conftest import DATA

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def least_of(n, links):
    up = list(range(n))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return [root(x) for x in range(n)]


# ---- Jaccard


def sets_of(text, words):
    w = WORD.findall((text or "").translate({c: c + 32 for c in range(65, 91)}))
    return {tuple(w[k : k + words]) for k in range(max(1, len(w) - words + 1))} if w else set()


@pytest.mark.parametrize("words,percent", [(3, 90), (5, 80)])
def test_jaccard_groups_equal_brute_force(spark, words, percent):
    rnd = random.Random(percent)
    vocabulary = [f"w{i}" for i in range(2000)]
    texts = [None, "", " \n", "One", "one", "a b", "a b c", "A b c"]
    for _ in range(25):
        base = [rnd.choice(vocabulary) for _ in range(rnd.choice([1, 4, 9, 15, 30, 80, 200]))]
        for _ in range(rnd.choice([1, 2, 6])):
            t = base[:]
            for _ in range(rnd.randint(0, max(1, len(t) // 30))):
                t[rnd.randrange(len(t))] = rnd.choice(vocabulary)
            texts.append(" ".join(t))
    sets = [sets_of(t, words) for t in texts]
    links = [(a, b) for a in range(len(texts)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    want = {k: (len(sets[k]), c) for k, c in enumerate(least_of(len(texts), links))}
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    assert {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard_join.jaccard_groups(df, words, percent).collect()} == want


def test_large_group_without_broadcasts(spark, monkeypatch):
    """A group of near copies, all sizes above the broadcast bounds."""
    monkeypatch.setattr(jaccard_join, "BROADCAST_BYTES", 0)
    base = [f"w{i}" for i in range(120)]
    rows = [(i, " ".join(base[:i] + [f"x{i}"] + base[i + 1 :])) for i in range(60)]
    found = {r["component_id"] for r in jaccard_join.jaccard_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert found == {0}


def test_jaccard_of_nothing_and_null_ids(spark):
    assert jaccard_join.jaccard_groups(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    rows = [(None, "a b c"), (4, "a b c"), (2, "a b c")]
    found = sorted(map(tuple, jaccard_join.jaccard_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=str)
    assert found == [(2, 1, 2), (4, 1, 2), (None, 1, None)]


def test_jaccard_of_repeated_rows(spark):
    """Equal rows stay rows; of different texts with one doc_id the first in order counts for all its rows."""
    rows = [(3, "a b c d"), (3, "a b c d"), (7, "z z z z"), (7, "a b c d"), (8, "z z z z"), (5, "q r")]
    found = sorted(map(tuple, jaccard_join.jaccard_groups(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    assert found == [(3, 2, 3), (3, 2, 3), (5, 1, 5), (7, 2, 3), (7, 2, 3), (8, 1, 8)]


def test_tiles_of_many_small_blocks(spark, monkeypatch):
    monkeypatch.setattr(jaccard_join, "BLOCK_TILES", 40)
    monkeypatch.setattr(jaccard_join, "PART_TILES", 50)
    rule = jaccard_join.Rule(3, 90)
    texts = [" ".join(f"w{(i // 3) * 50 + k}" for k in range(30 + i % 3)) for i in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = {}
    for i, text in enumerate(texts):
        data = np.frombuffer(text.encode(), np.uint8)
        for up, (tiles, enough) in enumerate(rule.tiles(next(rule.sets(data, np.asarray([0, len(data)]))))):
            for tile in tiles:
                want.setdefault(int(tile >> np.uint64(16)), []).append((i, up, enough))
    want = {t: ids for t, ids in want.items() if len(ids) > 1}
    met = Counter((i, up) for ids in want.values() for i, up, _ in ids)
    want = {t: {i for i, up, enough in ids if met[i, up] >= enough} for t, ids in want.items()}
    got = {}
    for row in jaccard_join.shared_tiles(df, rule, 2000).collect():
        got.setdefault(row["tile"], set()).add(row["v"])
    assert got and got == {t: ids for t, ids in want.items() if len(ids) > 1}


def test_components_of_a_long_chain(spark):
    rows = [(i, i + 1) for i in range(200)] + [(500, 501), (501, 500)]
    got = {r["id"]: r["component_id"] for r in components.components(spark.createDataFrame(rows, "u long, v long")).collect()}
    assert got == {**{i: 0 for i in range(201)}, 500: 500, 501: 500}


# ---- vectors


def test_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    centres = rng.normal(size=(40, 16))
    rows = [c + rng.normal(size=16) * s for c in centres for s in (0, 0, 0.05, 0.1, 0.2)]
    vectors = [[float(np.float32(x)) for x in r] for r in rows]
    vectors += [None, [0.0] * 16, [float("nan")] + [1.0] * 15, [float("inf")] * 16, [None] + [1.0] * 15, [1.0, 2.0], [2.0, 4.0], [3 * x for x in vectors[0]]]
    df = spark.createDataFrame(list(enumerate(vectors)), "vec_id long, embedding array<double>")
    usable = [k for k, v in enumerate(vectors) if v and all(x is not None and np.isfinite(x) for x in v) and any(v)]
    unit = {k: np.asarray(vectors[k]) / np.linalg.norm(vectors[k]) for k in usable}
    links = [(a, b) for a in usable for b in usable if a < b and len(unit[a]) == len(unit[b]) and unit[a] @ unit[b] >= 0.95]
    degree = Counter(x for pair in links for x in pair)
    group = least_of(len(vectors), links)
    found = {r["vec_id"]: r for r in vector_dedup.near_vectors(df).collect()}
    assert len(found) == len(vectors)
    assert sum(r["n_links"] for r in found.values()) >= 0.9 * 2 * len(links)
    assert all(r["n_links"] <= degree[k] for k, r in found.items())
    same = np.mean([found[k]["component_id"] == group[k] for k in found])
    assert same >= 0.9 and all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in found.values())


def test_no_vectors(spark):
    assert vector_dedup.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    assert vector_dedup.near_vectors(spark.createDataFrame([(1, None)], "vec_id long, embedding array<float>")).collect()[0]["n_links"] == 0


def pairs_and_cluster(pairs, lone, cluster, width=32, seed=7):
    """Unit vectors: pairs at cosine 0.952 to 0.97, lone ones, and a cluster of distinct near copies; and the number of pairs."""
    rng = np.random.default_rng(seed)
    unit = lambda x: x / np.sqrt((x * x).sum(-1, keepdims=True))
    a = unit(rng.normal(size=(pairs, width)))
    side = rng.normal(size=a.shape)
    side = unit(side - (side * a).sum(1, keepdims=True) * a)
    cos = rng.uniform(0.952, 0.97, (pairs, 1))
    b = cos * a + np.sqrt(1 - cos**2) * side
    near = unit(unit(rng.normal(size=width)) + rng.normal(size=(cluster, width)) * 0.001)
    return np.concatenate([a, b, unit(rng.normal(size=(lone, width))), near])


@pytest.mark.parametrize("pairs, cluster", [(60, 0), (300, 1500)], ids=["few links", "a cluster beside pairs"])
def test_links_of_pairs_are_found_whatever_else_there_is(spark, monkeypatch, pairs, cluster):
    monkeypatch.setattr(vector_dedup, "SAMPLE", 512)
    vectors = pairs_and_cluster(pairs, 4500 - 2 * pairs, cluster)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>")
    n = {r["vec_id"]: r["n_links"] for r in vector_dedup.near_vectors(df).collect()}
    assert sum(n[i] >= 1 for i in range(2 * pairs)) >= 0.99 * 2 * pairs
    assert all(n[i] == cluster - 1 for i in range(4500, 4500 + cluster))


def test_visits_are_the_most_that_any_group_size_needs():
    shares = {64: np.asarray([0, 1000.0, 0, 0, 0]), 1: np.asarray([0, 5.0, 0, 5.0, 0])}
    assert vector_dedup.visits_for(shares, 0.995) == 3
    assert vector_dedup.visits_for({1: np.asarray([0, 9.0, 0, 0, 1.0])}, 0.995) == 4


def test_a_bound_on_visits_makes_cells_larger_instead(spark, monkeypatch):
    monkeypatch.setattr(vector_dedup, "MOST_VISITS", 4)
    monkeypatch.setattr(vector_dedup, "SAMPLE", 512)
    vectors = pairs_and_cluster(150, 2200, 0)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>")
    n = {r["vec_id"]: r["n_links"] for r in vector_dedup.near_vectors(df).collect()}
    assert sum(n[i] >= 1 for i in range(300)) >= 297


# ---- mixing


def water(sizes, weights, total):
    target, open_ = {k: 0.0 for k in sizes}, set(sizes)
    rest = total
    while open_:
        level = rest / sum(weights[k] for k in open_)
        full = {k for k in open_ if level * weights[k] >= 2 * sizes[k]}
        if not full:
            for k in open_:
                target[k] = level * weights[k]
            break
        for k in full:
            target[k] = 2 * sizes[k]
            rest -= target[k]
        open_ -= full
    return target


@pytest.mark.parametrize("seed", range(3))
def test_targets_and_taken(spark, seed):
    rnd = random.Random(seed)
    names = ["a", "B", "é", None, "z"]
    rows = [(i, " ".join(["w"] * rnd.randint(0, 9)), rnd.choices(names, [1, 2, 40, 3, 9])[0]) for i in range(1500)] + [(9000, None, "a"), (9001, "\t\n", None)]
    found = mixing.mix_sources(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    sizes = Counter()
    for _, t, s in rows:
        sizes[s] += len(WORD.findall(t or ""))
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    want = water(sizes, {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}, 1.5 * sum(sizes.values()))
    taken = Counter()
    for r in found:
        assert abs(r["target"] - want[r["source"]]) < 1e-6 and 0 <= r["taken"] <= 2 * r["size"]
        taken[r["source"]] += r["taken"]
    large = [s for s in sizes if sizes[s] > 500]
    assert large and all(abs(taken[s] - want[s]) <= 0.15 * want[s] + 40 for s in large)
    again = mixing.mix_sources(spark.createDataFrame(rows[::-1], "doc_id long, text string, source string")).collect()
    assert sorted((r["doc_id"], r["taken"]) for r in found) == sorted((r["doc_id"], r["taken"]) for r in again)


def test_mixing_nothing_and_clashing_columns(spark):
    assert mixing.mix_sources(spark.createDataFrame([], "doc_id long, text string, source string")).count() == 0
    one = mixing.mix_sources(spark.createDataFrame([(1, "a", "s", 5)], "doc_id long, text string, source string, Target int"))
    assert [c.lower() for c in one.columns].count("target") == 1 and one.first()["taken"] in (1, 2)


# ---- chat


def test_round_trip_of_control_strings(spark):
    bad = ["</turn>", "### user: x", "\\b\\l", "\\", "a</turn>\n### assistant: b", "", None, "plain", "\n", "x" * 5000, "\\h#<"]
    rows = [(c, k, role, text) for c, texts in enumerate([bad, bad[::-1], ["plain", "talk"]]) for k, (role, text) in enumerate(zip(["user", "assistant", "sys: tem", None] * 3, texts))]
    made = chat_format.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    found = {r["conv_id"]: r for r in made.withColumn("turns", chat_format.parse(F.col("formatted"))).collect()}
    for c in range(3):
        mine = [((r or ""), (t or "")) for cc, _, r, t in rows if cc == c]
        assert [(t["role"], t["text"]) for t in found[c]["turns"]] == mine
    assert "\\" not in found[2]["formatted"]
    for c in range(3):
        f = found[c]["formatted"]
        spans = [f[s["start"] : s["start"] + s["length"]] for s in found[c]["loss_mask"]]
        plain = [s.replace("\\c", ":").replace("\\h", "#").replace("\\l", "<").replace("\\b", "\\") if c < 2 else s for s in spans]
        assert plain == [(t or "") for cc, _, r, t in rows if cc == c and r == "assistant"]


def test_no_conversations(spark):
    assert chat_format.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


# ---- packing


def tokens():
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


def test_faster_encoder_has_the_same_ids():
    import public_tokenizers

    slow, fast = tokens(), packing.Encoder(public_tokenizers.path("byte_bpe_50k.json"))
    assert fast.fast is not None
    rnd = random.Random(1)
    texts = ["", " ", "a", "it's  we'll\n\n\tgo", "<|endoftext|> x", "漢字 émigré 🙂 𝒳", "0123 456", "\x00\x7f\x80", "  " * 200, "ab" * 500]
    texts += ["".join(rnd.choice("abc ÄßéЖ漢🙂'.,\n\t 019") for _ in range(rnd.randint(1, 200))) for _ in range(300)]
    for t in texts:
        assert fast.ids(t).tolist() == slow.encode(t, add_special_tokens=False).ids


def test_pieces_fit_without_gaps(spark):
    rnd = random.Random(3)
    texts = [None, ""] + [" ".join(rnd.choice(["alpha", "beta", "x", "über"]) for _ in range(rnd.choice([1, 5, 90, 500, 3000]))) for _ in range(60)]
    rows = list(enumerate(texts)) + [(5, texts[5]), (None, "no id")]
    made = packing.pack_documents(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    t = tokens()
    want = Counter()
    for i, text in rows:
        ids = t.encode(text or "", add_special_tokens=False).ids + [2]
        first = (len(ids) - 1) % 1024 + 1
        cuts = [0, *range(first, len(ids) + 1, 1024)]
        for k, (a, b) in enumerate(zip(cuts, cuts[1:])):
            want[i, k, a, b - a, zlib.crc32(np.asarray(ids[a:b], "<u4").tobytes())] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in made) == want
    by = defaultdict(list)
    for r in made:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 1024
    assert len(by) <= sum(r["length"] for r in made) / 1024 * 1.05 + 1
    assert packing.pack_documents(spark.createDataFrame([], "doc_id long, text string")).count() == 0


def test_plan_uses_every_piece_once():
    rnd = random.Random(9)
    counts = Counter(min(1024, int(rnd.lognormvariate(6, 1)) + 1) for _ in range(20000))
    used = Counter()
    n = 0
    for lengths, times in packing.fill_plan(counts):
        assert sum(lengths) <= 1024
        n += times
        for x in lengths:
            used[x] += times
    assert used == counts and n <= sum(x * k for x, k in counts.items()) / 1024 * 1.01 + 1
    assert packing.fill_plan({}) == []


# ---- registry and pipeline


def test_every_operator_has_a_query():
    assert {int(n[2:].split("_")[0]) for n in registry.QUERIES} == set(range(1, 11))
    assert set(registry.ORACLES) <= set(registry.QUERIES)


def test_pipeline_against_brute_force(spark):
    import corpus_pipeline
    from signpart.llm import language_id

    assert [name for name, _ in corpus_pipeline.STAGES] == ["language ID", "line dedup", "n-gram Jaccard join", "mixing sources", "best-fit packing"]
    docs = store.table(spark, DATA, "documents")
    found = corpus_pipeline.run(spark, DATA).collect()

    named = {r["doc_id"]: r for r in language_id.identify(docs.select("doc_id", "text", "lang")).collect()}
    # Four languages: a share of 0.3 is 1.2 times the equal one.
    rows = [r for r in docs.collect() if named[r["doc_id"]]["lang_pred"] != "und" and (named[r["doc_id"]]["score"] >= 0.3 or named[r["doc_id"]]["score"] == 0)]
    strip = lambda s: s.strip(" \t\n\x0b\x0c\r").translate({c: c + 32 for c in range(65, 91)})
    seen = Counter(k for r in rows for k in {strip(x) for x in r["text"].split("\n")} if k)
    text = {r["doc_id"]: "\n".join(x for x in r["text"].split("\n") if not (strip(x) and seen[strip(x)] >= 10)) for r in rows}
    ids = sorted(text)
    sets = [sets_of(text[i], 5) for i in ids]
    links = [(a, b) for a in range(len(ids)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    kept = [ids[k] for k, c in enumerate(least_of(len(ids), links)) if c == k]
    source = {r["doc_id"]: r["source"] for r in rows}
    size = {i: len(WORD.findall(text[i])) for i in kept}
    sizes = Counter()
    for i in kept:
        sizes[source[i]] += size[i]
    order = sorted(sizes, key=lambda s: (s is None, (s or "").encode()))
    want = water(sizes, {s: (5, 2, 1)[k % 3] for k, s in enumerate(order)}, 1.5 * sum(sizes.values()))
    t, copies = tokens(), Counter()
    for i in kept:
        rate = want[source[i]] / sizes[source[i]] if sizes[source[i]] else 0.0
        chance = int(hashlib.md5(f"17:{i}".encode()).hexdigest()[:13], 16) / 2**52
        n = int(rate) + (chance < rate - int(rate))
        if n:
            copies[i, len(t.encode(text[i], add_special_tokens=False).ids) + 1] = n
    got = defaultdict(int)
    for r in found:
        got[r["doc_id"]] += r["length"]
    assert dict(got) == {i: n * tokens_ for (i, tokens_), n in copies.items()}


def test_language_stage_keeps_short_clean_texts(spark):
    import corpus_pipeline

    docs = store.table(spark, DATA, "documents").select("doc_id", "text", "lang", "source", "n_chars")
    odd = [(10**6 + i, t, None, "s", 1) for i, t in enumerate(["A.", "é", "x", "Ok", "12 34", "", None, "!?"])]
    both = docs.unionByName(spark.createDataFrame(odd, docs.schema)).withColumns({"score": F.lit("own"), "lang_pred": F.lit(5), "doc": F.lit(1)})
    kept = corpus_pipeline.known_language(spark, both, DATA)
    assert kept.columns == both.columns
    assert {r["doc_id"] - 10**6 for r in kept.where("doc_id >= 1000000").collect()} == {0, 1, 2, 3}


def test_stages_take_nulls_empty_tables_repeated_rows_and_any_columns(spark):
    import corpus_pipeline

    schema = "doc_id long, text string, lang string, source string, n_chars long, copy int, size int, class_id string, row int"
    rows = [(None, None, None, None, None, 1, 1, "c", 1), (1, "one two three", "en", None, 13, 1, 1, "c", 1), (1, "one two three", "en", None, 13, 1, 1, "c", 1), (2, "", None, "s", 0, 1, 1, "c", 1), (3, "vier fünf sechs " * 300, "de", "s", 1, 1, 1, "c", 1)]
    for given in (rows, []):
        docs = spark.createDataFrame(given, schema)
        for name, stage in corpus_pipeline.STAGES[:-1]:
            out = stage(spark, docs, DATA)
            assert out.columns == docs.columns, name
            found = out.collect()
            assert bool(found) == bool(given), name
        packed = corpus_pipeline.packed_sequences(spark, docs, DATA).collect()
        assert len({r["doc_id"] for r in packed}) == (4 if given else 0)
    docs = spark.createDataFrame(rows, schema)
    assert sorted(r["doc_id"] for r in corpus_pipeline.known_language(spark, docs, DATA).collect()) == [1, 1, 3]
    assert corpus_pipeline.one_of_each_group(spark, docs, DATA).count() == 5


def test_plan_uses_the_exact_complements():
    index = packing.SumIndex({700: 1, 300: 1, 24: 1, 200: 2, 100: 3}, 1024)
    assert index.exact(300) == (300,) and index.exact(324) == (300, 24) and index.exact(400) == (300, 100)
    assert index.exact(424) == (300, 100, 24) and index.exact(600) == (300, 200, 100) and index.exact(900) == (700, 200)
    index.take((300, 100))
    assert index.exact(400) == (200, 200) and index.exact(300) == (200, 100) and index.exact(324) == (200, 100, 24)
    index.take((200, 200))
    assert index.exact(400) is None and index.exact(200) == (100, 100) and index.largest(699) == 100
    assert packing.fill_plan({700: 4, 300: 4, 24: 4, 512: 3}) == [((700, 300, 24), 4), ((512, 512), 1), ((512,), 1)]


def test_ranks_of_a_hot_length_in_more_groups(spark):
    rows = [(i, 0, 0, 512 if i % 5 else 100, i) for i in range(400)]
    cut = spark.createDataFrame(rows, "doc_id long, piece int, start long, length long, ids_crc32 long")
    found = packing.pack(cut, salts=2, group_rows=30).collect()
    held = defaultdict(list)
    for r in found:
        held[r["sequence_id"]].append((r["offset"], r["length"]))
    for places in held.values():
        places.sort()
        assert [o for o, _ in places] == [sum(x for _, x in places[:k]) for k in range(len(places))] and sum(x for _, x in places) <= 1024
    assert sorted(r["doc_id"] for r in found) == list(range(400))


def test_mixing_with_helper_names_and_repeated_rows(spark):
    rows = [(1, "a b", "s", 1, 2), (1, "a b", "s", 1, 2), (2, "c", None, 3, 4)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, of_source int, copy int")
    found = mixing.mix_sources(df)
    assert [r["taken"] for r in found.where("doc_id = 1").collect()] in ([2, 2], [4, 4]) and found.count() == 3
    assert mixing.repeated(found, df.columns).columns == df.columns
