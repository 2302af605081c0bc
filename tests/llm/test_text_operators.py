"""Line dedup, substring dedup, fingerprints, language ID and LM scores against brute force."""

import hashlib
import math
import random
import re
from collections import Counter

import pytest
import xxhash
from pyspark.sql import functions as F

from signpart.llm import language_id, line_dedup, lm_score, order_minhash, packed_keys, substring_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")
#: Fixed texts: null, empty, white space, ties, repeats, other scripts.
ODD = [None, "", " \t\n ", "one", "one", "a b c", "Ünïcode words, 漢字 かな!", "x" * 3000, "\n\n\n", "tab\tand\x0bform\x0cfeed\r\nend"]


def frame(spark, rows, schema="doc_id long, text string"):
    return spark.createDataFrame(rows, schema)


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


# ---- lines


def lines_of(rows, min_docs):
    strip = lambda s: s.strip(" \t\n\x0b\x0c\r").translate({c: c + 32 for c in range(65, 91)})
    seen = Counter(k for _, t in rows for k in {strip(x) for x in (t or "").split("\n")} if k)
    out = {}
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if not (strip(x) and seen[strip(x)] >= min_docs)]
        out[i] = (len(lines), len(lines) - len(kept), "\n".join(kept))
    return out


@pytest.mark.parametrize("limit", [1000, 0], ids=["broadcast", "joined"])
def test_common_lines_go(spark, limit):
    rnd = random.Random(2)
    lines = ["Common Line", " common line\t", "other", "", "  ", "Ä ö", "last"] + [f"u{k}" for k in range(40)]
    rows = [(i, "\n".join(rnd.choice(lines) for _ in range(rnd.randint(1, 9)))) for i in range(30)] + [(100 + i, t) for i, t in enumerate(ODD)]
    found = line_dedup.line_dedup(frame(spark, rows), min_docs=4, broadcast_keys=limit).collect()
    assert {r["doc_id"]: (r["n_lines"], r["n_dropped"], r["text"]) for r in found} == lines_of(rows, 4)


def test_runs_compact_and_tell_new_lines(spark):
    index = line_dedup.LineRuns(spark, min_docs=4, fanout=2)
    for k in range(4):
        new = index.add(frame(spark, [(k, "same\nline %d" % k)]))
        assert new.count() == (2 if k == 0 else 1)
        assert index.common().count() == (1 if k == 3 else 0)
    assert [len(x) for x in index.levels] == [0, 0, 1] and index.merges == 3
    assert index.add(frame(spark, [(9, "same\nfresh\nfresh")])).count() == 1
    assert index.common().count() == 1


def test_order_and_number_of_batches_do_not_matter(spark):
    """Every batch goes through the runs; the common keys are those of plain totals."""
    rnd = random.Random(8)
    rows = [(i, "\n".join(f"l{rnd.randint(0, 40)}" for _ in range(rnd.randint(1, 6)))) for i in range(60)]
    want = None
    for parts in ([rows], [rows[k::7] for k in range(7)], [rows[k::7] for k in reversed(range(7))]):
        index = line_dedup.LineRuns(spark, min_docs=5, fanout=3)
        for part in parts:
            index.add(frame(spark, part))
        got = sorted(bytes(r[0]) for r in index.common().collect())
        assert want in (None, got) and len(set(got)) == len(got)
        want = got
        assert index.merges == (2 if len(parts) == 7 else 0)
    assert want


def test_line_dedup_compacts_on_its_way(spark, monkeypatch):
    held = []
    add = line_dedup.LineRuns.add_counts
    monkeypatch.setattr(line_dedup.LineRuns, "add_counts", lambda self, counts: (held.append(self), add(self, counts))[1])
    line_dedup.line_dedup(frame(spark, [(i, "x") for i in range(20)]))
    assert held[0].merges >= 1 and len(held) > held[0].fanout


@pytest.mark.parametrize("limit", [1000, 0], ids=["broadcast", "joined"])
def test_line_dedup_keeps_columns_of_any_name(spark, limit):
    rows = [(i, "same\nown %d" % i, i, i, "k", 7) for i in range(4)]
    df = frame(spark, rows, "doc_id long, text string, id int, drop int, key string, batch int")
    found = line_dedup.line_dedup(df, min_docs=4, broadcast_keys=limit)
    assert sorted(map(tuple, found.select(*df.columns).collect())) == [(i, "own %d" % i, i, i, "k", 7) for i in range(4)]


def test_line_dedup_of_nothing_and_of_clashing_columns(spark):
    assert line_dedup.line_dedup(frame(spark, [])).count() == 0
    extra = line_dedup.line_dedup(frame(spark, [(1, "a", 5), (None, None, None)], "doc_id long, text string, N_lines int"))
    assert extra.columns.count("n_lines") == 1 and extra.count() == 2


# ---- substrings


def substrings_of(rows, width):
    words = {i: WORD.findall(t or "") for i, t in rows}
    first = {}
    for i, w in words.items():
        for k in range(len(w) - width + 1):
            key = tuple(w[k : k + width])
            first[key] = min(i, first.get(key, i))
    out = {}
    for i, w in words.items():
        gone = set()
        for k in range(len(w) - width + 1):
            if first[tuple(w[k : k + width])] < i:
                gone |= set(range(k, k + width))
        out[i] = (len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone))
    return out


@pytest.mark.parametrize("width,gram", [(12, 3), (50, 10)])
def test_repeated_passages_go(spark, width, gram):
    rnd = random.Random(width)
    word = lambda: f"w{rnd.randint(0, 900)}"
    passages = [[word() for _ in range(rnd.randint(width - 1, 2 * width))] for _ in range(6)]
    rows = []
    for i in range(60):
        text = []
        for _ in range(rnd.randint(0, 4)):
            text += [word() for _ in range(rnd.randint(0, width))] + rnd.choice(passages)[rnd.choice([0, 0, 1, 3]) :]
        rows.append((i, rnd.choice([" ", "\n", "\t "]).join(text)))
    rows += [(200, " ".join(["same"] * 3 * width)), (201, " ".join(["same"] * (3 * width + 5))), (202, rows[0][1])] + [(300 + i, t) for i, t in enumerate(ODD)]
    found = substring_dedup.substring_dedup(frame(spark, rows), width, gram).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["text"]) for r in found} == substrings_of(rows, width)


def test_substring_dedup_of_nothing_and_null_ids(spark):
    assert substring_dedup.substring_dedup(frame(spark, [])).count() == 0
    long = " ".join(f"w{i}" for i in range(60))
    kept = {r["doc_id"]: r["n_removed"] for r in substring_dedup.substring_dedup(frame(spark, [(None, long), (5, long), (7, long)])).collect()}
    assert kept == {None: 0, 5: 0, 7: 60}


@pytest.mark.parametrize("batches", [1, 7])
def test_number_of_batches_does_not_matter(spark, monkeypatch, batches):
    """Passages that sit in part and as a whole in earlier and later batches."""
    held = []
    look_up = substring_dedup.FingerprintIndex.look_up
    monkeypatch.setattr(substring_dedup.FingerprintIndex, "look_up", lambda self, part: (held.append(self), look_up(self, part))[1])
    rnd = random.Random(3)
    passages = [[f"p{k}x{i}" for i in range(30)] for k in range(4)]
    rows = []
    for i in range(70):
        words = [f"u{i}x{j}" for j in range(rnd.randint(0, 20))]
        p = rnd.choice(passages)
        a = rnd.randint(0, 15)
        rows.append((rnd.randint(0, 10**6), " ".join(words + p[a : a + rnd.randint(10, 30)] + words[:5] + rnd.choice(passages)[:14])))
    found = substring_dedup.substring_dedup(frame(spark, rows), 12, 3, batches, fanout=3).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["text"]) for r in found} == substrings_of(rows, 12)
    assert len(held) == batches and held[0].merges == (2 if batches == 7 else 0)


def test_substring_dedup_keeps_columns_of_any_name(spark):
    rows = [(i, "a b c d e f g h", i, 5, "x", 3) for i in range(3)]
    df = frame(spark, rows, "doc_id long, text string, row long, begins int, of_doc string, batch int")
    found = substring_dedup.substring_dedup(df, 4, 2)
    assert sorted(map(tuple, found.select(*df.columns).collect())) == [(i, "" if i else "a b c d e f g h", i, 5, "x", 3) for i in range(3)]


# ---- fingerprints


def test_fingerprints_follow_edits(spark):
    rnd = random.Random(4)
    base = [f"w{rnd.randint(0, 10**6)}" for _ in range(300)]
    swapped = base[150:] + base[:150]
    other = [f"v{rnd.randint(0, 10**6)}" for _ in range(300)]
    changed = base[:]
    changed[7] = "new"
    rows = [(1, " ".join(base)), (2, " ".join(changed)), (3, " ".join(swapped)), (4, " ".join(other)), (5, " ".join(base))]
    made = {r["doc_id"]: r["fingerprint"] for r in order_minhash.fingerprints(frame(spark, rows), ["doc_id"], components=128).collect()}
    like = lambda a, b: sum(x == y for x, y in zip(made[a], made[b])) / 128
    assert like(1, 5) == 1 and like(1, 4) == 0
    # A swap of halves keeps the set of k-mers, but not the order of about half of the pairs.
    assert like(1, 2) > 0.9 > 0.75 > like(1, 3) > 0.25


def test_occurrences_are_numbered(spark):
    rows = [(1, "a b a b a b"), (2, "a b a b")]
    from pyspark.sql import functions as F

    got = {r["doc_id"]: [x >> 24 for x in r["e"]] for r in frame(spark, rows).select("doc_id", order_minhash.elements(F.col("text")).alias("e")).collect()}
    assert len(set(got[1])) == 5 and set(got[2]) < set(got[1])


def test_ring_and_edited_texts(spark):
    rows = [(i * 3, t) for i, t in enumerate([*ODD, "a longer text with several words", "漢字" * 9])]
    found = {r["doc_id"]: r for r in order_minhash.document_fingerprints(frame(spark, rows)).collect()}
    order = sorted(rows, reverse=True)
    for k, (i, t) in enumerate(order):
        t, following = t or "", order[(k + 1) % len(order)][1] or ""
        cut = len(t) // 3
        assert found[i]["n_chars"] == len(t)
        assert found[i]["edited_sha256"] == sha(t[: len(t) - cut] + following[:cut])
    assert found[9]["fingerprint"] == found[12]["fingerprint"] and found[9]["near_next"] <= 1
    assert order_minhash.document_fingerprints(frame(spark, [])).count() == 0
    assert order_minhash.document_fingerprints(frame(spark, [(1, "only one")])).first()["near_next"] == 1


def signed64(x):
    return x - (1 << 64) if x >= 1 << 63 else x


def xx(*values):
    """Spark's 64-bit hash of text, longs and ints (as (value, bytes)), one after the other; None is passed over."""
    seed = 42
    for v in values:
        if v is not None:
            data = v.encode() if isinstance(v, str) else (v[0] % (1 << 8 * v[1])).to_bytes(v[1], "little")
            seed = xxhash.xxh64_intdigest(data, seed)
    return signed64(seed)


def murmur(*words):
    """Spark's 32-bit hash of values given as lists of 32-bit words."""
    mask, h = 0xFFFFFFFF, 42
    rotl = lambda x, r: (x << r | x >> 32 - r) & mask
    for value in words:
        for w in value:
            h = (rotl(h ^ rotl(w * 0xCC9E2D51 & mask, 15) * 0x1B873593 & mask, 13) * 5 + 0xE6546B64) & mask
        h ^= 4 * len(value)
        for shift, factor in ((16, 0x85EBCA6B), (13, 0xC2B2AE35)):
            h = (h ^ h >> shift) * factor & mask
        h ^= h >> 16
    return h


def fingerprint_of(text, k=order_minhash.K, components=order_minhash.COMPONENTS):
    """The same fingerprint from a plain reading of the method."""
    low = (1 << 24) - 1
    words = re.split(r"[\x20\x09-\x0D]+", (text or "").strip(" \t\n\x0b\x0c\r"))
    seen, elements = Counter(), []
    for i in range(max(1, len(words) - k + 1)):
        high = xx(*words[i : i + k]) >> 24
        elements.append((high if not seen[high] else xx((high, 8), (seen[high], 4)) >> 24, i))
        seen[high] += 1
    least = [min((xx((e, 8), (j, 4)) & ~low) | i for e, i in elements) for j in range(2 * components)]
    out = []
    for a, b in zip(least[::2], least[1::2]):
        first = (a & low) <= (b & low)
        a, b = (a >> 24, b >> 24) if first else (b >> 24, a >> 24)
        out.append(murmur(*([x & 0xFFFFFFFF, x >> 32 & 0xFFFFFFFF] for x in (a, b)), [int(first)]))
    return out


def test_fingerprints_equal_a_plain_reading(spark):
    """All columns, with repeated rows, null ids, one doc_id with many texts, and likenesses."""
    rnd = random.Random(9)
    rows = [(i, " ".join(rnd.choice(["a", "b", "c", "dd", "é"]) for _ in range(rnd.randint(0, 30)))) for i in range(12)]
    rows += [(40, t) for t in ODD] + [(41, "same row"), (41, "same row"), (41, "same row"), (None, "no id"), (None, "no id"), (None, "other")]
    rows += [(99, f"text {i} of one id") for i in range(60)]
    ring = {r["at"]: r for r in order_minhash.in_ring(frame(spark, rows)).collect()}
    assert Counter((r["doc_id"], r["text"]) for r in ring.values()) == Counter((i, t or "") for i, t in rows) and len(ring) == len(rows)
    assert sorted(r["next_at"] for r in ring.values()) == sorted(ring)
    walk, at = [], max(ring, key=lambda a: (ring[a]["doc_id"] or -1))
    for _ in ring:
        assert (ring[at]["next_id"], ring[at]["next_text"]) == (ring[ring[at]["next_at"]]["doc_id"], ring[ring[at]["next_at"]]["text"])
        walk.append(ring[at]["doc_id"])
        at = ring[at]["next_at"]
    start = next(k for k in range(len(walk)) if walk[k] == 99 and walk[k - 1] is None)
    assert walk[start:] + walk[:start] == sorted((i for i, _ in rows if i is not None), reverse=True) + [None] * 3
    hexed = lambda f: "".join(f"{c:08X}" for c in f)
    like = lambda a, b: sum(x == y for x, y in zip(a, b)) / len(a)
    want = Counter()
    for r in ring.values():
        cut = len(r["text"]) // 3
        changed = r["text"][: len(r["text"]) - cut] + r["next_text"][:cut]
        own, other, after = fingerprint_of(r["text"]), fingerprint_of(changed), fingerprint_of(r["next_text"])
        want[r["doc_id"], len(r["text"]), sha(changed), hexed(own), hexed(other), like(own, other), like(own, after)] += 1
    assert Counter(map(tuple, order_minhash.document_fingerprints(frame(spark, rows)).collect())) == want


# ---- languages


def test_languages_are_told_and_letterless_texts_are_not(spark):
    rnd = random.Random(7)
    parts = {"aa": ["the", "ing", "ou", "thr", "st"], "bb": ["der", "sch", "ich", "ung", "ß"], "cc": ["ción", "que", "los", "ñ", "el"]}
    rows = []
    for i in range(90):
        lang = rnd.choice(sorted(parts))
        rows.append((i, " ".join("".join(rnd.choice(parts[lang]) for _ in range(3)) for _ in range(40)), lang))
    rows += [(900, "12345 --- 67", "aa"), (901, None, None), (902, "", "bb"), (903, "漢字だけ", None)]
    df = frame(spark, rows, "doc_id long, text string, lang string")
    found = {r["doc_id"]: r for r in language_id.identify(df).collect()}
    assert all(found[i]["lang_pred"] == lang for i, _, lang in rows[:90])
    assert [found[i]["lang_pred"] for i in (900, 901, 902)] == ["und"] * 3 and found[903]["lang_pred"] in parts
    assert all(0 <= r["score"] <= 1 for r in found.values())


def test_languages_equal_a_plain_count(spark):
    """Every prediction from sets of languages looked up n-gram by n-gram; and the held-out documents are told right."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    learned = docs.where(~language_id.held_out()).select(F.col("doc_id").alias("key"), "text", "lang")
    model = language_id.fit(learned)
    columns = [[int(w) for w in plane] for plane in model.table]
    holds = lambda i, at: columns[i // 64][at] >> i % 64 & 1
    chance = [(sum(holds(i, at) for at in range(1 << 16)) / (1 << 16)) ** 2 for i in range(len(model.languages))]

    def plain(text):
        if not any(c.isalpha() for c in text or ""):
            return "und", 0.0
        folded = [b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in text.encode()]
        seen, hits = 0, [0] * len(chance)
        for size in (3, 4):
            for k in range(len(folded) - size + 1):
                code = sum(b << 8 * i for i, b in enumerate(folded[k : k + size])) ^ size * 0x01000193
                places = [code * odd % (1 << 32) >> 16 for odd in (0x9E3779B1, 0x85EBCA6B)]
                seen += 1
                for i in range(len(chance)):
                    hits[i] += all(holds(i, at) for at in places)
        real = [max(0.0, (h - seen * c) / (1 - c)) for h, c in zip(hits, chance)]
        best = real.index(max(real))
        return model.languages[best], max(real) / sum(real) if sum(real) else 0.0

    some = [(k, t) for k, t in enumerate([*ODD, "A.", "é", "Zz", *(r["text"] for r in docs.orderBy("doc_id").limit(25).collect())])]
    for r in language_id.predict(frame(spark, some), model).collect():
        lang, score = plain(r["text"])
        assert r["lang_pred"] == lang and math.isclose(r["score"], score, rel_tol=1e-9, abs_tol=1e-12)
    told = [r["lang_pred"] == r["lang"] for r in language_id.predict(docs.where(language_id.held_out() & F.col("lang").isNotNull()), model).collect() if r["lang_pred"] != "und"]
    assert len(told) > 200 and sum(told) / len(told) > 0.97


def test_language_id_of_nothing_and_of_clashing_columns(spark):
    assert language_id.identify(frame(spark, [], "doc_id long, text string, lang string")).count() == 0
    rows = [(1, "the cat and the dog", "en", 1), (1, "the cat and the dog", "en", 1), (None, "der Hund und", "de", 2), (2, None, None, 3)]
    found = language_id.identify(frame(spark, rows, "doc_id long, text string, lang string, Score int"))
    assert found.count() == 4 and [c.lower() for c in found.columns].count("score") == 1


def test_nothing_learned(spark):
    df = frame(spark, [(1, "some text", None)], "doc_id long, text string, lang string")
    assert [tuple(r)[-2:] for r in language_id.identify(df).collect()] == [("und", 0.0)]


def test_one_table_serves_more_than_64_languages():
    import numpy as np

    grams = {f"l{k:02d}": {3: [k * 7919 + 5], 4: []} for k in range(70)}
    filters = language_id.Filters.build(grams)
    assert filters.table.shape[0] == 2
    code = np.asarray([69 * 7919 + 5], dtype=np.uint32)
    words = [np.bitwise_and.reduce([filters.table[p][s] for s in language_id._slots(code, 3)])[0] for p in (0, 1)]
    assert words[1] >> np.uint64(69 - 64) & np.uint64(1)


# ---- scores


def test_stupid_backoff(spark):
    rnd = random.Random(1)
    rows = [(i, " ".join(rnd.choice("abcdefgh") for _ in range(rnd.randint(0, 30)))) for i in range(25)] + [(100 + i, t) for i, t in enumerate(ODD)]
    words = {i: WORD.findall(t or "") for i, t in rows}
    one, two = Counter(x for w in words.values() for x in w), Counter(p for w in words.values() for p in zip(w, w[1:]))
    total = sum(one.values())
    found = {r["doc_id"]: r for r in lm_score.lm_scores(frame(spark, rows), order=2).collect()}
    for i, w in words.items():
        logs, back = [], 0
        for k, x in enumerate(w):
            if k == 0:
                s = one[x] / total
            elif two[w[k - 1], x] >= 2:
                s = two[w[k - 1], x] / one[w[k - 1]]
            else:
                s, back = 0.4 * one[x] / total, back + 1
            logs.append(math.log(s))
        assert (found[i]["n_words"], found[i]["n_backoff"]) == (len(w), back)
        assert (found[i]["score"] is None) if not w else math.isclose(found[i]["score"], sum(logs) / len(w), rel_tol=1e-9)


@pytest.mark.parametrize("order,block,part", [(1, 1 << 20, 1000), (3, 1 << 20, 1000), (3, 150, 40), (5, 400, 90)])
def test_stupid_backoff_of_any_order(spark, monkeypatch, order, block, part):
    """In one block and partition, and in several of each."""
    monkeypatch.setattr(lm_score, "BLOCK_BYTES", block)
    monkeypatch.setattr(lm_score, "PARTITION_GRAMS", part)
    rnd = random.Random(4)
    rows = [(i, " ".join(rnd.choice("abc") for _ in range(rnd.randint(0, 30)))) for i in range(25)] + [(100 + i, t) for i, t in enumerate(ODD)]
    words = {i: WORD.findall(t or "") for i, t in rows}
    seen = Counter(tuple(w[k : k + n]) for w in words.values() for n in range(1, order + 1) for k in range(len(w) - n + 1))
    total = sum(len(w) for w in words.values())

    def scored(gram):
        if len(gram) == 1:
            return seen[gram] / total, 0
        if seen[gram] >= 2:
            return seen[gram] / seen[gram[:-1]], 0
        s, steps = scored(gram[1:])
        return 0.4 * s, steps + 1

    for r in lm_score.lm_scores(frame(spark, rows), order=order).collect():
        w = words[r["doc_id"]]
        each = [scored(tuple(w[max(0, k + 1 - order) : k + 1])) for k in range(len(w))]
        assert (r["n_words"], r["n_backoff"]) == (len(w), sum(b for _, b in each))
        assert (r["score"] is None) if not w else math.isclose(r["score"], sum(math.log(s) for s, _ in each) / len(w), rel_tol=1e-9)


def test_scores_of_nothing_of_repeated_rows_and_of_clashing_columns(spark):
    assert lm_score.lm_scores(frame(spark, [])).count() == 0
    rows = [(1, "a b a b", 5, 1, "x"), (1, "a b a b", 5, 1, "x"), (None, "a b", 6, 2, "y"), (None, None, 6, 2, "y")]
    found = lm_score.lm_scores(frame(spark, rows, "doc_id long, text string, block int, n_words int, part string")).collect()
    assert sorted((r["doc_id"] or 0, r["n_words"], r["n_backoff"], r["score"] is None) for r in found) == [(0, 0, 0, True), (0, 2, 0, False), (1, 4, 0, False), (1, 4, 0, False)]


def test_packed_keys_round_trip():
    import numpy as np

    keys = np.unique(np.random.default_rng(3).integers(0, 2**64 - 1, 5000, dtype=np.uint64))
    assert (packed_keys.unpacked(packed_keys.packed(keys)) == keys).all()
    assert len(packed_keys.unpacked(packed_keys.packed(keys[:0]))) == 0
