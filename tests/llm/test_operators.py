"""The training-data operators on small tables: brute force, round trips, and the defined results of odd rows."""

import hashlib
import math
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from pairsample.llm import byte_bpe, decontamination, embedding_dedup, html_text, language_id, language_model, license_scan, line_dedup, order_minhash, token_counts
from pairsample.llm.common import Scratch, components
from pairsample.llm.crf import Chain, padded

WORDS = [a + b for a in "bcdfglmnprstvz" for b in ("a", "e", "o", "an", "er")]


def prose(rng, n):
    return " ".join("".join(rng.choice(WORDS) for _ in range(rng.randint(1, 3))) for _ in range(n))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and blank texts, repeated rows, special strings, a long run without blanks, and a column of a clashing name."""
    rows = [(1, "one two  three\n\nfour <s>"), (1, "one two  three\n\nfour <s>"), (2, None), (3, ""), (4, " \n\t "), (None, "no id"), (5, "a" * 3000), (6, "<|endoftext|> ünïcode ▁ 漢字"), (7, None)]
    return spark.createDataFrame([(d, t, "x", -1) for d, t in rows], "doc_id long, text string, n_tokens string, n_dropped int")


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string")


def test_token_counts_follow_the_library(odd, empty):
    model = token_counts.load(None)
    got = [tuple(r) for r in token_counts.count_tokens(odd, limit=100).collect()]
    want = [(r.doc_id, len((r.text or "").encode()), len(model.encode(r.text or "")), len(model.encode(r.text or "")) > 100) for r in odd.collect()]
    assert sorted(got, key=str) == sorted(want, key=str)
    assert token_counts.count_tokens(empty).count() == 0


def test_bpe_follows_the_library_and_round_trips(odd, empty):
    import public_tokenizers
    import tiktoken

    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_bpe.read_ranks(None), special_tokens={})
    rng = random.Random(2)
    encoder = byte_bpe.Encoder(None, 1000)
    texts = ["".join(rng.choices("aaabcde '\t\n sll²½\x1c\x85é漢🙂", k=rng.randint(0, 120))) for _ in range(500)]
    assert encoder.encode(texts) == [np.array(library.encode_ordinary(t), "<u4").tobytes() for t in texts]
    for r in byte_bpe.decode(byte_bpe.encode(odd)).join(odd.select("doc_id", "text").distinct(), "doc_id").collect():
        assert bytes(r.decoded) == (r.text or "").encode()
    assert byte_bpe.encode(empty).count() == 0


def brute_lines(rows):
    """The kept lines of each row, every pair of lines compared."""

    def near(a, b):
        if a == b:
            return True
        x, y = a.split(" "), b.split(" ")
        if abs(len(x) - len(y)) > 1 or max(len(x), len(y)) < 5:
            return False
        best = list(range(len(y) + 1))
        for i, p in enumerate(x, 1):
            row = [i]
            for j, q in enumerate(y, 1):
                row.append(min(best[j] + 1, row[-1] + 1, best[j - 1] + (p != q)))
            best = row
        return best[-1] <= 1

    seen, out = [], {}
    for d, text in sorted(rows):
        kept = []
        for line in text.split("\n"):
            bare = line.strip(line_dedup.BLANKS)
            if bare and any(near(bare, s) for s in seen):
                continue
            kept.append(line)
            if bare:
                seen.append(bare)
        # dropped lines still count as earlier ones
        seen += [x for x in (y.strip(line_dedup.BLANKS) for y in text.split("\n")) if x and x not in seen]
        out[d] = "\n".join(kept)
    return out


def test_line_dedup_against_brute_force(spark, odd, empty):
    rng = random.Random(4)
    base = [prose(rng, rng.randint(1, 12)) for _ in range(25)]

    def edited(line):
        words = line.split(" ")
        k = rng.randrange(len(words))
        kind = rng.randrange(4)
        return " ".join(words[:k] + words[k + 1 :] if kind == 0 else words[:k] + ["new"] + words[k:] if kind == 1 else words[:k] + ["other"] + words[k + 1 :] if kind == 2 else words) or "x"

    rows = [(d, "\n".join([edited(rng.choice(base)) for _ in range(rng.randint(1, 6))] + ["", "  "])) for d in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r.text for r in line_dedup.dedup_lines(docs).collect()}
    assert got == brute_lines(rows)
    kept = line_dedup.dedup_lines(odd).collect()
    assert len(kept) == odd.count() and {r.n_dropped for r in kept} == {0}
    assert line_dedup.dedup_lines(empty).count() == 0


def test_near_duplicates_against_brute_force(spark, odd, empty):
    rng = random.Random(5)
    originals = [prose(rng, rng.randint(90, 140)).split() for _ in range(12)]
    rows = []
    for k in range(60):
        words = list(rng.choice(originals))
        for _ in range(rng.choice([0, 1, 2, 4])):
            words[rng.randrange(len(words))] = "changed"
        rows.append((k, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    hasher = order_minhash.Hasher()
    words = {k: hasher.hashes(t.split()).astype("<u4") for k, t in rows}
    parent = {k: k for k in words}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    pairs = [(a, b) for a in words for b in words if a < b]
    for (a, b), (close, _) in zip(pairs, order_minhash.near([(words[a], words[b]) for a, b in pairs], 0.8), strict=True):
        if close:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    found = {r.doc_id: (r.cluster_id, r.kept) for r in order_minhash.near_duplicates(docs).collect()}
    assert found == {k: (root(k), root(k) == k) for k in words}
    strange = {r.doc_id: r.cluster_id for r in order_minhash.near_duplicates(odd).collect()}
    assert strange == {1: 1, 2: 2, 3: 2, 4: 4, 5: 5, 6: 6, 7: 2}
    assert order_minhash.near_duplicates(empty).count() == 0


def with_words(base, at, mark):
    return " ".join(f"{mark}{k}" if k in at else w for k, w in enumerate(base))


def test_near_chain_and_star_stay_whole(spark):
    rng = random.Random(21)
    base = prose(rng, 300).split()
    # a chain in one bucket: the middle text is near both ends, the ends not to each other
    chain = [with_words(base, set(range(0, 45)), "x"), " ".join(base), with_words(base, set(range(255, 300)), "y")]
    rows = list(enumerate(chain))
    # a star: each copy is near the centre, which has the largest id, and near no other copy
    centre = prose(rng, 300).split()
    rows += [(100 + k, with_words(centre, set(rng.sample(range(300), 40)), f"s{k}q")) for k in range(60)] + [(500, " ".join(centre))]
    got = {r.doc_id: r.cluster_id for r in order_minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), k=3, sketches=32).collect()}
    assert got == {d: 0 if d < 100 else 100 for d, _ in rows}


def test_near_pairs_in_a_crowded_bucket_are_all_met(spark):
    rng = random.Random(22)
    # all texts share a passage, so buckets are crowded with texts far from each other
    passage = prose(rng, 90).split()
    bodies = [passage + prose(rng, 60).split() for _ in range(120)]
    rows = [(k, " ".join(b)) for k, b in enumerate(bodies)] + [(500 + k, with_words(b, set(rng.sample(range(150), 24)), f"e{k}q")) for k, b in enumerate(bodies)]
    got = {r.doc_id: r.cluster_id for r in order_minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), k=3, sketches=32).collect()}
    assert sum(got[500 + k] == got[k] for k in range(120)) >= 114
    assert all(got[k] == k for k in range(120))


def test_near_recall_from_the_threshold_on(spark):
    rng = random.Random(23)
    rows, cuts = [], {}
    for k in range(400):
        # half the pairs are short; all are between 0.8 and 0.9
        n = rng.randint(5, 60) if k % 2 else rng.randint(61, 300)
        base = prose(rng, n).split()
        edits = rng.randint(max(1, math.ceil(n * 0.1)), n // 5) if n >= 10 else 1
        rows += [(2 * k, " ".join(base)), (2 * k + 1, with_words(base, set(rng.sample(range(n), edits)), f"e{k}q"))]
        cuts[k] = n
    got = {r.doc_id: r.cluster_id for r in order_minhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    found = {k: got[2 * k + 1] == 2 * k for k in cuts}
    assert all(found[k] for k in cuts if cuts[k] <= order_minhash.SHORT)
    assert sum(found.values()) >= 0.97 * len(found)


def test_banded_alignment_is_exact():
    rng = random.Random(6)

    def distance(a, b):
        best = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            row = [i]
            for j, y in enumerate(b, 1):
                row.append(min(best[j] + 1, row[-1] + 1, best[j - 1] + (x != y)))
            best = row
        return best[-1]

    pairs = []
    for _ in range(200):
        a = [rng.randint(1, 6) for _ in range(rng.randint(1, 60))]
        b = [x if rng.random() < 0.9 else rng.randint(1, 6) for x in a if rng.random() < 0.95] or [1]
        pairs.append((np.array(a, np.uint32), np.array(b, np.uint32)))
    for (a, b), (close, d) in zip(pairs, order_minhash.near(pairs, 0.8), strict=True):
        true = distance(a.tolist(), b.tolist())
        assert close == (true <= int(0.2 * max(len(a), len(b)) + 1e-9)) and (not close or d == true)


def interpolated(tokens, used, held):
    """Scores of texts (tokens by id) by plain counting, and weights learned token by token; ``held`` are the ids kept from the counts at first."""

    def counted(ids):
        words = Counter(w for k in ids for w in tokens[k])
        pairs = Counter(p for k in ids for p in zip([language_model.END, *tokens[k]], tokens[k]))
        total = sum(words.values())
        return lambda u, w: (words[u], pairs[u, w] / max(words[u], 1), words[w] / max(total, 1)), len(words)

    def step(p):
        return 2.0 ** (-round(-language_model.FINE * math.log2(p)) / language_model.FINE) if p else 0.0

    model, kinds = counted([k for k in used if k not in held])
    seen = [model(u, w) for k in held for u, w in zip([language_model.END, *tokens[k]], tokens[k])]
    weights = {}
    for b in {int(math.log2(c + 1)) for c, _, _ in seen}:
        values = [(step(p2), step(p1), 1 / (kinds + 1)) for c, p2, p1 in seen if int(math.log2(c + 1)) == b]
        w = [0.5, 0.4, 0.1]
        for _ in range(60):
            parts = [[x * y for x, y in zip(w, v)] for v in values]
            w = [(sum(p[k] / sum(p) for p in parts) + 0.5) / (len(values) + 1.5) for k in range(3)]
        weights[b] = w
    model, kinds = counted(used)
    scores = {}
    for k, words in tokens.items():
        scores[k] = 0.0
        for u, w in zip([language_model.END, *words], words):
            c, p2, p1 = model(u, w)
            a, b, g = weights.get(int(math.log2(c + 1)), (0.5, 0.4, 0.1))
            scores[k] += math.log10(a * p2 + b * p1 + g / (kinds + 1))
    return scores


@pytest.mark.parametrize("fan", [2048, 3, 2])
def test_language_model_against_brute_force(spark, empty, monkeypatch, fan):
    monkeypatch.setattr(language_model, "FAN", fan)  # one, two and three levels
    rng = random.Random(7)
    rows = [(k, prose(rng, rng.randint(0, 40)) if k % 9 else None) for k in range(80)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    train = F.crc32(F.col("doc_id").cast("string")) % 7 != 2
    got = {r.doc_id: r for r in language_model.score_texts(docs, train).collect()}
    tokens = {k: (t or "").encode().lower().split() + [language_model.END] for k, t in rows}
    used = [k for k in tokens if zlib.crc32(str(k).encode()) % 7 != 2]
    away = docs.where(F.pmod(F.xxhash64(F.lit("held"), F.col("doc_id").cast("string")), F.lit(10)) == 0)
    scores = interpolated(tokens, used, {r.doc_id for r in away.collect()} & set(used))
    count = Counter(w for k in used for w in tokens[k])
    total, kinds = sum(count.values()), len(count)
    for k, words in tokens.items():
        assert got[k].n_tokens == len(words) and got[k].n_known == sum(count[w] > 0 for w in words) and got[k].train_tokens == total
        assert got[k].base_score == pytest.approx(sum(math.log10((count[w] + 1) / (total + kinds + 1)) for w in words))
        assert got[k].score == pytest.approx(scores[k])
    assert language_model.score_texts(empty, train).count() == 0


def test_messages_of_a_block_do_not_grow_with_the_shards():
    for shards in (8, 2048, 2049, 5000, 17_000_000):
        levels, fan = language_model.levels_of(shards)
        assert fan <= language_model.FAN and fan**levels >= shards > fan ** (levels - 1)


def test_mixture_weights_fit_their_source():
    rng = np.random.default_rng(8)
    p2, p1 = rng.uniform(0.001, 1, 5000), rng.uniform(0.001, 1, 5000)
    weights = language_model.learn_weights(np.full(5000, 3), language_model.level(p2), np.full(5000, -1), np.ones(5000, np.int64), 1e-6)
    assert weights[3, 0] > 0.9 and weights[3].sum() == pytest.approx(1)
    assert np.allclose(weights[0], [0.5, 0.4, 0.1])
    assert p1.size


def test_byte_planes_round_trip():
    x = np.sort(np.random.default_rng(9).integers(0, 2**63, 1000).astype(np.uint64))
    assert (language_model.unpack_sorted(language_model.pack_sorted(x), 1000) == x).all()
    assert (language_model.unpack(language_model.pack(x), 1000) == x).all()


def test_leaks(spark, odd, empty):
    rng = random.Random(10)
    items = [(k, prose(rng, rng.randint(8, 40))) for k in range(12)] + [(90, None), (91, "..."), (92, "two words")]
    docs = []
    for d in range(60):
        body = prose(rng, 80).split()
        if d % 3 == 0:
            words = items[d % 12][1].upper().split()
            cut = rng.choice([0, 0, len(words) // 10, len(words) // 2])
            body[10:10] = words[: len(words) - cut]
        docs.append((d, " ".join(body)))
    docs.append((60, "here Two, WORDS! appear"))
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    frame = spark.createDataFrame(docs, "doc_id long, text string")

    def runs(text):
        words = [w for w in "".join(c.lower() if c.isalnum() else " " for c in text or "").split()]
        return lambda k: {tuple(words[i : i + k]) for i in range(len(words) - k + 1)}, len(words)

    want = set()
    for item, text in items:
        of, n = runs(text)
        if n:
            mine = of(min(n, 5))
            want |= {(d, item, len(mine), len(mine & runs(t)[0](min(n, 5)))) for d, t in docs if len(mine & runs(t)[0](min(n, 5))) >= 0.8 * len(mine) - 1e-9}
    got = {(r.doc_id, r.item_id, r.n_shingles, r.n_found) for r in decontamination.find_leaks(frame, benchmark).collect()}
    assert got == want and (60, 92, 1, 1) in got
    left = decontamination.remove_leaks(frame, benchmark)
    assert {r.doc_id for r in left.collect()} == {d for d, _ in docs} - {x[0] for x in want}
    assert decontamination.find_leaks(odd, benchmark).count() == 0 and decontamination.remove_leaks(odd, benchmark).count() == odd.count()
    assert decontamination.find_leaks(frame, benchmark.limit(0)).count() == 0 and decontamination.find_leaks(empty, benchmark).count() == 0


def test_language_id(spark, odd, empty):
    rng = random.Random(11)
    tongue = {"aa": [w + "ik" for w in WORDS], "bb": [w + "oum" for w in WORDS]}
    say = lambda k, n: " ".join(rng.choice(tongue[k]) for _ in range(n))
    rows = [(d, say("ab"[d % 2] * 2, 30), "ab"[d % 2] * 2) for d in range(60)] + [(100, None, "aa"), (101, "text", None)]
    model = language_id.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    tests = spark.createDataFrame([(d, say("ab"[d % 2] * 2, 20)) for d in range(20)], "doc_id long, text string")
    for r in language_id.identify(tests, model).collect():
        assert r.lang_pred == "ab"[r.doc_id % 2] * 2 and 0.5 < r.score <= 1
    mixed = spark.createDataFrame([(1, say("aa", 15) + " " + say("bb", 15))], "doc_id long, text string")
    labels = [r.lang for r in language_id.label_words(mixed, model).orderBy("position").collect()]
    assert sum(x == y for x, y in zip(labels, ["aa"] * 15 + ["bb"] * 15, strict=True)) >= 28
    got = {r.doc_id: r.lang_pred for r in language_id.identify(odd, model).collect()}
    assert got[2] == got[3] == got[4] == language_id.UNKNOWN
    assert language_id.keep_identified(odd, model).columns == odd.columns
    assert language_id.identify(empty, model).count() == 0
    nothing = language_id.train(empty.withColumn("lang", F.lit(None).cast("string")))
    assert {r.lang_pred for r in language_id.identify(odd, nothing).collect()} == {language_id.UNKNOWN}


def test_lettered_junk_has_no_language(spark):
    rng = random.Random(24)
    tongue = {k: [w + end for w in WORDS] for k, end in zip(("aa", "bb", "cc", "dd"), ("ik", "oum", "est", "ul"), strict=True)}
    rows = [(d, " ".join(rng.choice(tongue[k]) for _ in range(60)), k) for d in range(30) for k in tongue]
    model = language_id.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    clean = [(d, " ".join(rng.choice(tongue[k]) for _ in range(40))) for d, k in enumerate(list(tongue) * 5)]
    junk = [(100 + d, " ".join("".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=rng.randint(2, 10))) for _ in range(40))) for d in range(20)]
    junk += [(200, "kaikki ihmiset syntyvät vapaina ja tasavertaisina arvoltaan ja oikeuksiltaan"), (201, "και το είναι της που με για από στην")]
    kept = language_id.keep_identified(spark.createDataFrame(clean + junk, "doc_id long, text string"), model)
    assert {r.doc_id for r in kept.collect()} == {d for d, _ in clean}


def test_chain_against_enumeration():
    rng = np.random.default_rng(12)
    chain = Chain(4, 3)
    chain.step, chain.start = rng.normal(size=(3, 3)).astype(np.float32), rng.normal(size=3).astype(np.float32)
    lengths = np.array([4, 2])
    emission, where = padded(rng.normal(size=(6, 3)).astype(np.float32), lengths)
    probs = chain.forward_backward(emission, lengths)
    best = chain.viterbi_all(emission, lengths)
    for n, size in enumerate(lengths):
        paths = np.array(np.meshgrid(*[range(3)] * size, indexing="ij")).reshape(size, -1).T
        score = np.array([chain.start[p[0]] + sum(emission[t, n, p[t]] for t in range(size)) + sum(chain.step[p[t - 1], p[t]] for t in range(1, size)) for p in paths])
        weight = np.exp(score - score.max())
        assert best[n] == paths[score.argmax()].tolist()
        for t in range(size):
            assert np.allclose(probs[t, n], [weight[paths[:, t] == k].sum() / weight.sum() for k in range(3)], atol=1e-5)


def brute_links(vectors):
    good = {k: np.array(v) / np.linalg.norm(v) for k, v in vectors.items() if v is not None and None not in v and np.isfinite(v).all() and np.any(v)}
    return {(a, b) for a in good for b in good if a < b and len(good[a]) == len(good[b]) and good[a] @ good[b] >= 0.9}


def test_vector_links(spark):
    rng = np.random.default_rng(13)
    vectors = {}
    for g in range(12):
        center = rng.standard_normal(32)
        for _ in range(8):
            vectors[len(vectors)] = (center / np.linalg.norm(center) + rng.choice([0.001, 0.3]) * rng.standard_normal(32) / np.sqrt(32)).tolist()
    vectors |= {200: None, 201: [0.0] * 32, 202: [None] + [1.0] * 31, 203: [float("nan")] * 32, 204: [1.0], 205: vectors[0]}
    frame = spark.createDataFrame(list(vectors.items()) + [(205, vectors[205])], "vec_id long, embedding array<double>")
    links = brute_links(vectors)
    counts = Counter(x for pair in links for x in pair)
    got = {r.vec_id: r for r in embedding_dedup.linked_vectors(frame).collect()}
    assert set(got) == set(vectors)
    assert all(got[k].n_links <= counts[k] for k in vectors)
    assert sum(got[k].n_links for k in vectors) >= 0.9 * 2 * len(links)
    assert all(got[k].n_links == 0 and got[k].component_id == k and got[k].kept for k in (200, 201, 202, 203))
    assert embedding_dedup.linked_vectors(frame.limit(0)).count() == 0


def test_licenses(spark, odd):
    files = [
        (1, "/a/LICENSE", "MIT License\n\nReleased under the MIT License."), (2, "/a/b/c.py", "code"), (3, "/a/d.py", "# Licensed under the Apache License, Version 2.0.\nimport os, sys, json, random\ndef first(x, y, z): return compute(x) + other(y) - third(z)\nprint(first(alpha, beta, gamma))"),
        (4, "/e/f.py", "nothing"), (5, None, None), (6, "/a/b/COPYING", "All rights reserved."), (7, "/ab/x", ""),
    ]
    got = {r.doc_id: (r.license, r.basis, r.from_path) for r in license_scan.scan_licenses(spark.createDataFrame(files, "doc_id long, path string, text string")).collect()}
    assert got[1][:2] == ("MIT", "file") and got[2] == ("All-rights-reserved", "inherited", "/a/b/COPYING")
    assert got[3][:2] == ("Apache-2.0", "statement") and got[4][:2] == got[5][:2] == got[7][:2] == (None, "none")
    assert license_scan.scan_licenses(odd.withColumn("path", F.lit("/x/y"))).where("license IS NOT NULL").count() == 0


def test_full_license_files_are_inherited(spark):
    texts = license_scan.full_texts()
    files = [(k, f"/{name}/LICENSE", "Copyright (c) 2020 Some One\n\n" + text) for k, (name, text) in enumerate(texts)]
    files += [(100 + k, f"/{name}/src/a.py", "print(1)") for k, (name, _) in enumerate(texts)]
    got = {r.doc_id: (r.license, r.basis, r.from_path) for r in license_scan.scan_licenses(spark.createDataFrame(files, "doc_id long, path string, text string")).collect()}
    for k, (name, _) in enumerate(texts):
        assert got[k] == (name, "file", f"/{name}/LICENSE") and got[100 + k] == (name, "inherited", f"/{name}/LICENSE")


def test_main_text(spark):
    chain = html_text.train()
    pages = list(html_text.labelled_pages(60, seed=77))
    wrong = sum(a != b for (_, want), got in zip(pages, html_text.label_pages(chain, [p for p, _ in pages]), strict=True) for a, b in zip(want, got, strict=True))
    assert wrong <= 0.03 * sum(len(p) for p, _ in pages)
    page = (
        '<html><head><title>T</title><script>var a="</p>";</script></head><body><nav><ul><li><a href=/x>Home</a></li></ul></nav><div class="cookie-notice">We use cookies</div>'
        "<article><h1>Head &amp; tail</h1><p>First  <b>bold\ntext.<br><p>Second &eacute;.</article><aside>Related things</aside><section id=comments><div class=comment><p>Nice one</p></div></section>"
        "<footer>&copy; 2020 us</footer>"
    )
    frame = spark.createDataFrame([(1, "u", page), (2, "v", None), (None, None, ""), (4, "w", "<p")], "page_id long, url string, html string")
    got = {r.page_id: (r.text, r.n_chars) for r in html_text.extract(frame, chain).collect()}
    assert got[1][0] == "Head & tail\nFirst bold text.\nSecond é." and got[1][1] == len(got[1][0])
    assert got[2] == got[None] == ("", 0)


def test_components(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(0, 40)] + [(100, 90), (90, 95), (7, 7), (None, 1)], "a long, b long")
    got = {r.node: r.component for r in components(Scratch(spark, "test"), edges).collect()}
    assert got == {**{k: 0 for k in range(41)}, 90: 90, 95: 90, 100: 90}


def test_pipeline_on_a_small_corpus(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(14)
    bench = [(k, prose(rng, 20)) for k in range(3)]
    texts = ["\n".join(prose(rng, 12) for _ in range(4)) for _ in range(12)]
    texts[3] = texts[1]  # a copy goes
    texts[5] = texts[5] + "\n" + bench[0][1]  # a leak goes
    texts[6] = "123 456"  # no language
    rows = [(k, t, "xx", "s", len(t)) for k, t in enumerate(texts)] + [(50, None, None, None, None)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(bench, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert set(got) == {0, 1, 2, 4, 7, 8, 9, 10, 11}
    assert all(got[k].decoded_sha256 == hashlib.sha256(texts[k].encode()).hexdigest() for k in got)
    assert len(corpus_pipeline.STAGES) == 5
