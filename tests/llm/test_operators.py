"""Each operator against brute force or an exact library, on given rows and on odd ones."""

import hashlib
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from triplefed.llm import chat_format, common, license_scan, mixing, near_duplicates, packing, quality_rules, token_count, toxicity, url_filter, vector_search

WORDS = re.compile(r"[^\x20\x09-\x0D]+").findall
ODD = [
    (1, None, "en", None, None), (2, "", "en", "a", 0), (3, "   \n\t ", None, "a", 6), (4, "one", "en", "b", 3), (5, "one", "en", "b", 3),
    (6, "Ünï çödé ΑΣ İ ½ ٣ 日本 <|endoftext|> \x1c x", "de", None, 9), (7, "ab " * 30_000, "en", "b", 90_000), (8, "a b c d e f g h i\n" * 40, "en", "b", 1),
    (9, "GNU General Public License, gnu general PUBLIC license; CC BY", "en", "c", 1), (10, "one", "en", None, 1),
]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet").limit(150).unionByName(spark.createDataFrame([(10_000 + r[0], *r[1:]) for r in ODD], SCHEMA)).withColumn("size", F.lit("clash")).withColumn("rank", F.lit(1)).cache()


@pytest.fixture(scope="module")
def texts(docs):
    return {r["doc_id"]: r["text"] or "" for r in docs.collect()}


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_url_rules_and_terms(spark):
    urls = {
        "http://a.org/x": ("a.org", "/x", "org/", "allow"), "HTTP://EXAMPLE.org/es/1": ("example.org", "/es/1", "example.org/es/", "block"),
        "x://www.example.org/en/12?q": ("www.example.org", "/en/12", "example.org/en/1", "block"), "http://notexample.org/es/": ("notexample.org", "/es/", "org/", "allow"),
        "http://b.com/fr/adult": ("b.com", "/fr/adult", "com/fr/", "allow"), "http://b.com/de/#x": ("b.com", "/de/", "com/de/", "block"),
        "http://b.com/adult-x": ("b.com", "/adult-x", None, "block"), "http://b.com/adults": ("b.com", "/adults", None, "block"), "http://b.com/adultery": ("b.com", "/adultery", None, "allow"),
        "http://cheap.com/cheap": ("cheap.com", "/cheap", None, "allow"), "http://cheap-pills.com": ("cheap-pills.com", "", None, "block"),
        "http://x.net/CASINO_win": ("x.net", "/CASINO_win", None, "block"), "http://x.net/poker": ("x.net", "/poker", None, "allow"), "http://x.net/poker/lotto": ("x.net", "/poker/lotto", None, "block"), "http://long.net/" + "a-" * 600_000 + "porn": ("long.net", "/" + "a-" * 600_000 + "porn", None, "block"), "nothing": ("", "", None, "allow"), None: ("", "", None, "allow"), "": ("", "", None, "allow"), "http://org": ("org", "", None, "allow"),
    }
    df = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.filter_urls(df).collect()}
    assert [got[i] for i in range(len(urls))] == list(urls.values())
    assert url_filter.filter_urls(df.limit(0)).count() == 0
    twice = url_filter.filter_urls(df.unionByName(df).select("url", F.lit(1).alias("page_id"))).collect()
    assert len(twice) == 2 * len(urls) and len({tuple(r) for r in twice}) <= len(urls)


def test_vocabulary_forms():
    assert url_filter.inflected("bet", "s,2ing") == ["bet", "bets", "betting"] and url_filter.inflected("free", "bies") == ["free", "freebies"]
    assert url_filter.inflected("gambl", "e,ing") == ["gambl", "gamble", "gambling"] and url_filter.inflected("hot-line", "-") == ["hot-line", "hotline"]
    strict, soft = url_filter.read_vocabulary(["# remark", "", "strict a,s b", "2 c,s a"])
    assert strict == ("a", "as", "b") and soft == {"c": 2, "cs": 2}


def brute_targets(sizes):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: i % 3 + 1 for i, s in enumerate(names)}
    total, target, left = sum(sizes.values()), {}, set(names)
    while left:
        rest = total - sum(target.values())
        share = {s: rest * weight[s] / sum(weight[x] for x in left) for s in left}
        over = {s for s in left if share[s] > 3 * sizes[s]}
        if not over:
            return target | share
        target |= {s: 3.0 * sizes[s] for s in over}
        left -= over
    return target


def test_mixing(docs, texts, empty):
    got = mixing.mix(docs).collect()
    again = {(r["doc_id"], r["taken"]) for r in mixing.mix(docs.repartition(7)).collect()}
    assert {(r["doc_id"], r["taken"]) for r in got} == again
    sizes = Counter()
    for r in got:
        assert r["size"] == len(WORDS(texts[r["doc_id"]])) and 0 <= r["taken"] <= 3 * r["size"] and r["taken"] == r["size"] * r["passes"]
        sizes[r["source"]] += r["size"]
    want = brute_targets(sizes)
    taken, largest = Counter(), Counter()
    for r in got:
        assert r["target"] == pytest.approx(want[r["source"]]) and r["source_size"] == sizes[r["source"]]
        taken[r["source"]] += r["taken"]
        largest[r["source"]] = max(largest[r["source"]], r["size"])
    for s in sizes:
        assert abs(taken[s] - want[s]) <= 2 * max(largest.values())
    assert sum(taken.values()) <= sum(sizes.values())
    assert mixing.mix(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0
    assert mixing.mixed_documents(docs).columns == docs.columns and mixing.mixed_documents(docs).count() == sum(r["passes"] for r in got)


def test_chat_round_trip(spark):
    said = [("user", "\\### Assistant: </turn> ok"), ("assistant", "\\### Assistant: </turn> ok"), ("tool: ### x\\", " </turn>\n### User: "), (None, None), ("assistant", ""), ("system", "日本 \\"), ("assistant", "b" * 5000)]
    df = spark.createDataFrame([(5, i, r, t, 1) for i, (r, t) in enumerate(said)] + [(None, 1, "user", "x", 1), (6, 1, "assistant", "z", 1), (6, 1, "assistant", "z", 1)], "conv_id long, turn long, role string, text string, ids int")
    formatted = chat_format.format_chat(df).where("conv_id = 5").collect()
    c = chat_format.codec(token_count.tokenizer_path("byte_bpe_50k.tiktoken"))
    whole = b"".join(c.text(r["ids"]) for r in formatted).decode()
    assert list(chat_format.parse(whole)) == [(r or "", t or "") for r, t in said]
    got = {r["conv_id"]: r for r in chat_format.read_back(chat_format.format_chat(df)).collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    learned = "".join(t for r, t in said if r == "assistant")
    assert got[5]["n_turns"] == 7 and got[5]["turns_sha256"] == sha("".join(f"{r or ''}\n{t or ''}\n" for r, t in said))
    assert got[5]["loss_sha256"] == sha(learned) and got[5]["loss_chars"] == len(learned) and got[5]["formatted_chars"] == len(whole)
    assert got[None]["n_turns"] == 1 and got[6]["loss_chars"] == 2
    assert chat_format.read_back(chat_format.format_chat(df.limit(0))).count() == 0


def test_chat_with_other_keys_and_a_very_long_turn(spark):
    long = "word " * 260_000 + "### User: x"
    df = spark.createDataFrame([("a", 1, "user", "x"), ("a", 2, "assistant", long), (None, 1, "assistant", "y"), ("b", 1, "assistant", "z"), ("b", 1, "assistant", "z")], "conv_id string, turn int, role string, text string")
    got = {r["conv_id"]: r for r in chat_format.read_back(chat_format.format_chat(df)).collect()}
    assert got["a"]["loss_chars"] == len(long) and got["a"]["loss_sha256"] == hashlib.sha256(long.encode()).hexdigest()
    assert got[None]["loss_chars"] == 1 and got["b"]["n_turns"] == 2


def kneser_ney(toxic, ordinary, every):
    """The differences of words and pairs, word by word: (history or None, word) to value."""
    pairs = [Counter(p for text in texts for p in zip(text, text[1:])) for texts in (toxic, ordinary)]
    before = {}
    for text in every:
        for w in text[:1]:
            before.setdefault(w, set())
        for h, w in zip(text, text[1:]):
            before.setdefault(w, set()).add(h)
    shared = {w: 1 + min(2, len(b)) for w, b in before.items()}
    z = sum(shared.values()) + 1
    cut = lambda c: toxicity.discounts([sum(v == k for v in c.values()) for k in (1, 2, 3, 4)])
    off = lambda v, d: d[min(v, 3) - 1] if v else 0.0
    word, unknown, models = [], [], []
    for c in pairs:
        follows = Counter(w for _, w in c)
        d, n = cut(follows), sum(follows.values())
        left = sum(off(v, d) for v in follows.values())
        word.append(lambda w, follows=follows, d=d, n=n, left=left: (follows[w] - off(follows[w], d) + left * shared[w] / z) / n)
        unknown.append(left / n)
        e = cut(c)
        uses, spare = Counter(), Counter()
        for (h, _), v in c.items():
            uses[h] += v
            spare[h] += off(v, e)
        models.append(lambda h, w, c=c, e=e, uses=uses, spare=spare, p=word[-1]: (c[h, w] - off(c[h, w], e) + spare[h] * p(w)) / uses[h] if uses[h] else p(w))
    words = {w for c in pairs for _, w in c}
    alone = {w: np.log(word[0](w) / word[1](w)) - np.log(unknown[0] / unknown[1]) for w in words}
    out = {(None, w): v for w, v in alone.items()}
    for h, w in {*pairs[0], *pairs[1]}:
        if pairs[0][h, w] + pairs[1][h, w] >= 2:
            out[h, w] = np.log(models[0](h, w) / models[1](h, w)) - alone[w]
    return out


def test_toxicity_models_by_brute_force(spark):
    rng = random.Random(9)
    vocabulary = [f"w{chr(97 + i)}" for i in range(14)]
    texts = [[rng.choice(vocabulary[:9] if i % 3 else vocabulary[4:]) for _ in range(rng.randint(0, 25))] for i in range(60)]
    toxic, ordinary = texts[:45:3], [x for i, x in enumerate(texts[:45]) if i % 3]
    hashes = toxicity.Hashes()
    frame = lambda rows: spark.createDataFrame(rows, "__text string, __toxic int")
    pairs = toxicity.materialize(toxicity.pair_counts(frame([(" ".join(x), 1) for x in toxic] + [(" ".join(x), 0) for x in ordinary])))
    shared = toxicity.materialize(toxicity.shared_counts(spark.createDataFrame([(" ".join(x),) for x in texts], "text string")))
    rows = toxicity.differences(pairs, shared, 0.0)
    got = {(r["h"], r["w"]): r["value"] for r in rows.collect()}
    key = lambda w: None if w is None else hashes[w]
    want = {(key(h), key(w)): v for (h, w), v in kneser_ney(toxic, ordinary, texts).items()}
    assert want.keys() >= got.keys() and all(abs(v) < 1e-12 for k, v in want.items() if k not in got)
    assert all(got[k] == pytest.approx(want[k], abs=1e-9) for k in got)
    # the model on every worker, and its table met by hash
    docs = spark.createDataFrame([(i, " ".join(x)) for i, x in enumerate(texts)] + [(99, None), (100, " ".join(texts[3]))], "id long, __text string")
    found = [sorted((r["id"], r["__n"], *(round(v, 4) for v in r["__e"])) for r in toxicity.Scorer(docs, rows, n).evidence(docs, (0.0, 0.7)).collect()) for n in (10**6, 0)]
    assert found[0] == found[1] and len(found[0]) == 62


def test_toxicity_held_out(spark, docs, empty):
    rng = random.Random(3)
    plain = [f"w{i}" for i in range(300)]
    made = []
    for i in range(600):
        words = rng.choices(plain, k=rng.randint(30, 120))
        bad = i % 4 == 0
        if bad:
            for _ in range(max(2, len(words) // 20)):
                words[rng.randrange(len(words))] = rng.choice(["foul", "vile", "nasty"])
        made.append((i, " ".join(words), int(bad)))
    d = spark.createDataFrame([(i, t) for i, t, _ in made], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in made] + [(0, None), (None, 1)], "doc_id long, toxic int")
    got = {r["doc_id"]: r for r in toxicity.score(d, labels).collect()}
    held = [(got[i]["predicted"], y) for i, _, y in made if zlib.crc32(str(i).encode()) % 5 == 0]
    assert all(got[i]["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) for i in got)
    assert sum(p == y for p, y in held) / len(held) > 0.95
    # labels of held-out rows change nothing
    flipped = labels.withColumn("toxic", F.when(toxicity.held_out(), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    assert {r["doc_id"]: r["score"] for r in toxicity.score(d, flipped).collect()} == {i: r["score"] for i, r in got.items()}
    odd = toxicity.score(docs, labels).collect()
    assert len(odd) == docs.count() and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in odd)
    assert toxicity.score(empty, labels).count() == 0 and {r["score"] for r in toxicity.score(docs, labels.limit(0)).collect()} == {0.0}


def test_licences(spark, docs, texts, empty):
    split = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+").findall
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for r in license_scan.scan(docs).collect():
        words = split(texts[r["doc_id"]].translate(lower))
        places, labels = [], set()
        for phrase, label in license_scan.BASE.items():
            p = phrase.split()
            found = [i for i in range(len(words)) if words[i:i + len(p)] == p]
            places += found
            labels |= {label} if found else set()
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == (len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels)))
        assert labels <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1
    text = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation. CC-BY-NC 4.0"
    one = license_scan.scan(spark.createDataFrame([(1, text)], "doc_id long, text string")).collect()[0]
    assert one["labels"] == "cc-by,cc-by-nc,mit-text" and one["base_labels"] == "cc-by"
    assert license_scan.scan(empty).count() == 0


def test_licence_index_finds_what_a_look_at_every_place_finds():
    index = license_scan.Index(license_scan.TEMPLATES)
    rng = random.Random(4)
    parts = [list(x.words) for x in license_scan.TEMPLATES]
    for _ in range(300):
        words = []
        for _ in range(rng.randint(1, 6)):
            p = list(rng.choice(parts))
            if rng.random() < 0.5:  # a word changed, left out or put in
                i = rng.randrange(len(p))
                p[i:i + rng.randint(0, 1)] = rng.choice([[], ["other"], [p[i], p[i]]])
            words += p + ["the"] * rng.randint(0, 2)
        every = [(k, s) for k in range(len(parts)) for s in range(len(words)) if index.stands(words, k, s)]
        assert index.scan(words) == every
    # all looked-up words of a template have to agree on where it starts
    assert index.starts(0, {"gnu": [5, 9], "general": [6], "public": [7], "license": [8, 12]}) == {5}
    assert index.starts(0, {"gnu": [5], "general": [7], "public": [7], "license": [8]}) == set()


def brute_groups(texts, words, percent):
    hashes = near_duplicates.WordHashes()
    sets = {}
    for i, t in texts.items():
        w = [x.lower() if x.isascii() else x.translate({k: k + 32 for k in range(65, 91)}) for x in WORDS(t)]
        sets[i] = {tuple(w[k:k + words]) for k in range(max(1, len(w) - words + 1))} if w else set()
        assert len(sets[i]) == len(near_duplicates.shingles(t, words, hashes))
    ids = sorted(sets)
    group = {i: i for i in ids}
    for k, i in enumerate(ids):
        for j in ids[k + 1:]:
            both = len(sets[i] & sets[j])
            if sets[i] and sets[j] and 100 * both >= percent * (len(sets[i]) + len(sets[j]) - both) and group[i] != group[j]:
                low, high = sorted((group[i], group[j]))
                group = {x: low if g == high else g for x, g in group.items()}
    return {i: (len(sets[i]), group[i]) for i in ids}


@pytest.mark.parametrize("words,percent,rows,depth", [(3, 85, 4096, 6), (5, 80, 24, 2)])
def test_near_duplicates(spark, docs, texts, words, percent, rows, depth):
    rng = random.Random(5)
    base = [f"t{rng.randrange(500)}" for _ in range(200)]
    more = {}
    for i in range(40):
        copy = list(base)
        for _ in range(i % 9):
            copy[rng.randrange(200)] = f"n{i}"
        more[20_000 + i] = " ".join(copy)
    every = {**texts, **more}
    df = docs.select("doc_id", "text", "size").unionByName(spark.createDataFrame([(k, v, "x") for k, v in more.items()], "doc_id long, text string, size string"))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_duplicates.duplicate_groups(df, words, percent, node_rows=rows, depth=depth).collect()}
    assert got == brute_groups(every, words, percent)


def boilerplate_pairs(n):
    """2 n texts of 198 words that share 160; texts 2 i and 2 i + 1 share 176, a similarity of 0.8, others one of 0.678."""
    shared = [f"b{k}" for k in range(160)]
    return {2 * i + h: " ".join(shared + [f"p{i}x{k}" for k in range(16)] + [f"u{i}x{h}x{k}" for k in range(22)]) for i in range(n) for h in (0, 1)}


def test_near_duplicates_in_large_nodes(spark):
    made = boilerplate_pairs(250)
    df = spark.createDataFrame(list(made.items()), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_duplicates.duplicate_groups(df, 1, 80, node_rows=32).collect()}
    # sketches may miss a link at the very threshold, nodes may not
    assert all(got[i] in (i, i - i % 2) for i in made) and sum(got[i] == i - 1 for i in made) >= 0.99 * len(made) / 2


def test_trees_follow_from_recall():
    for similarity, depth, recall in ((0.8, 2, 0.9999), (0.85, 2, 0.9999), (0.8, 6, 0.99)):
        n = near_duplicates.trees_for(similarity, depth, recall)
        missed = 1 - similarity**depth
        assert missed**n <= 1 - recall < missed ** (n - 1)
    assert near_duplicates.trees_for(1.0, 2, 0.9999) == 1


def test_near_duplicates_without_rows(spark, empty):
    assert near_duplicates.duplicate_groups(empty).count() == 0
    odd = spark.createDataFrame([(None, "a b c"), (1, None), (2, None)], "doc_id long, text string")
    got = sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in near_duplicates.duplicate_groups(odd).collect()), key=repr)
    assert got == [(1, 1, True), (2, 2, True), (None, None, True)]


def test_near_duplicates_of_repeated_ids(spark):
    a, b = " ".join(f"a{i}" for i in range(60)), " ".join(f"b{i}" for i in range(60))
    near = lambda x, k: x.replace(f"{x[0]}7 ", f"{x[0]}{k} ")
    rows = [(1, a), (1, b), (1, b), (2, near(a, 900)), (3, near(b, 901)), (4, near(b, 902)), (5, "one text"), (5, "one text")]
    got = sorted(tuple(r) for r in near_duplicates.duplicate_groups(spark.createDataFrame(rows, "doc_id long, text string"), 1, 80).collect())
    assert [r[0] for r in got] == [1, 2, 3, 4, 5]
    with_a, with_b = {1: 1, 2: 1, 3: 3, 4: 3, 5: 5}, {1: 1, 2: 2, 3: 1, 4: 1, 5: 5}
    assert {r[0]: r[2] for r in got} in (with_a, with_b)


def test_token_counts(docs, texts, empty):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(token_count.tokenizer_path("byte_bpe_50k.json"))
    for cache in (token_count.CACHE, 50):
        for r in token_count.count_tokens(docs, cache=cache).collect():
            t = texts[r["doc_id"]]
            n = len(lib.encode(t, add_special_tokens=False).ids)
            assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(t.encode()), n, n > 512)
    assert token_count.count_tokens(empty).count() == 0


def test_packing(docs, texts, empty):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(token_count.tokenizer_path("word_bpe_49k.json"))
    got = packing.pack(docs).collect()
    by_doc, by_sequence = {}, {}
    for r in got:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_sequence.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert by_doc.keys() == texts.keys()
    total = 0
    for i, t in texts.items():
        ids = np.array([*lib.encode(t, add_special_tokens=False).ids, 1], "<u4")
        total += len(ids)
        for k, r in enumerate(sorted(by_doc[i], key=lambda r: r["piece"])):
            part = ids[k * 4096:(k + 1) * 4096]
            assert (r["piece"], r["start"], r["length"], r["ids_crc32"]) == (k, k * 4096, len(part), zlib.crc32(part.tobytes()))
    for pieces in by_sequence.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 4096
    assert len(by_sequence) <= -(-total // 4096) + 1
    assert packing.pack(empty).count() == 0


def best_fit(lengths, capacity):
    gaps = []
    for n in sorted(lengths, reverse=True):
        fits = [g for g in gaps if g >= n]
        if fits:
            gaps.remove(min(fits))
            gaps.append(min(fits) - n)
        else:
            gaps.append(capacity - n)
    return len(gaps)


@pytest.mark.parametrize("part_rows", [200_000, 50])
def test_rounds_come_near_best_fit_decreasing(spark, monkeypatch, part_rows):
    monkeypatch.setattr(packing, "PART_ROWS", part_rows)
    rng = random.Random(2)
    # a third of one length, many of length 1, full ones
    lengths = [rng.randint(1, 40) for _ in range(400)] + [13] * 250 + [1] * 80 + [40] * 20
    df = spark.createDataFrame(list(enumerate(lengths)), "id long, size long")
    sequences = {}
    for r in packing.best_fit(df, 40).collect():
        sequences.setdefault(r["sequence"], []).append(r["id"])
    assert sorted(i for s in sequences.values() for i in s) == list(range(len(lengths)))
    assert all(sum(lengths[i] for i in s) <= 40 for s in sequences.values())
    least = best_fit(lengths, 40)
    assert len(sequences) <= 1.02 * least + 1


def test_a_sweep_gives_each_piece_the_smallest_free_gap(spark):
    gaps = spark.createDataFrame([(100, 9), (101, 5), (102, 5), (103, 2)], "sequence long, gap long")
    pieces = spark.createDataFrame([(0, 7), (1, 5), (2, 4), (3, 4), (4, 1)], "id long, size long")
    got = {r["id"]: r["sequence"] for r in packing.sweep(gaps, pieces, 4, 5, 7).where("kind = 1").collect()}
    # one of the pieces of 4 finds every gap that holds it taken
    assert got[0] == 100 and {got[1], got[2] or got[3]} == {101, 102} and None in (got[2], got[3]) and got[4] == 103


def test_encoder_agrees_with_the_library():
    from tokenizers import Tokenizer

    path = token_count.tokenizer_path("word_bpe_49k.json")
    lib, mine = Tokenizer.from_file(path), packing.encoder(path)
    same = lambda t: mine.encode(t) == np.array(lib.encode(t, add_special_tokens=False).ids, "<u4").tobytes()
    assert all(same(f"ab{c}cd {c} 1{c}") for c in map(chr, range(128)))
    assert all(same(f"é ab{chr(c)}cd {chr(c)}1{chr(c)}\u0301 A{chr(c)}") for c in range(0x80, 0x3000) if not 0xD800 <= c < 0xE000)
    rng = random.Random(7)
    some = [chr(c) for c in (*range(32, 127), 9, 10, 13, 28, 31, 0xE9, 0xDF, 0x130, 0x3A3, 0x3C3, 0x7FD, 0xC3C, 0x301, 0x1100, 0x1161, 0xAC00, 0x4E2D, 0x0E01, 0x1F600, 0x2028, 0xA0)]
    for _ in range(1500):
        assert same("".join(rng.choice(some) for _ in range(rng.randint(1, 30))))


def test_quality_counts(docs, texts, empty):
    for r in quality_rules.judge(docs).collect():
        t = texts[r["doc_id"]]
        w = WORDS(t)
        windows = [tuple(w[i:i + 8]) for i in range(len(w) - 7)]
        twice = {x for x, n in Counter(windows).items() if n > 1}
        covered = {k for i, x in enumerate(windows) if x in twice for k in range(i, i + 8)}
        lines = [x for x in t.split("\n") if WORDS(x)]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), sum(t.count(x) for x in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)), r["doc_id"]
        assert r["base_failed"] == (len(w) < 20 or 100 * len(covered) > 30 * len(w)) and not (r["base_failed"] and r["kept"])
    assert quality_rules.judge(empty).count() == 0
    good = quality_rules.good_documents(docs)
    assert good.columns == docs.columns and good.count() == quality_rules.judge(docs).where("kept").count()


def test_quality_keeps_prose_and_rejects_junk(spark):
    prose = "It is a truth that the house of the old man stood in a wide field, and to the eye of a child it was as large as a hill. For years it was that way, and the wind in the grass is what I remember. " * 1
    words = "the river and of a road that goes to town in rain it is for all people near home".split()
    rng = random.Random(1)
    long = prose + " ".join(rng.choice(words) + rng.choice(["", "", "", ",", "."]) for _ in range(300))
    junk = " ".join(f"{rng.randrange(10**6):06d}##$$%%|<>" for _ in range(200))
    got = {r["doc_id"]: r["kept"] for r in quality_rules.judge(spark.createDataFrame([(1, long), (2, junk)], "doc_id long, text string")).collect()}
    assert got == {1: True, 2: False}


def test_vector_search(spark, sf):
    given = spark.read.parquet(f"{sf}/embeddings.parquet")
    odd = spark.createDataFrame([(9000, None), (9050, [0.0] * 64), (9001, [float("nan")] * 64), (9002, [1.0, None] * 32), (9003, [1.0])] + [(9100 + i, [1.0] + [0.0] * 63) for i in range(12)], "vec_id long, embedding array<float>")
    df = given.select("vec_id", "embedding").unionByName(odd).withColumn("rank", F.lit(1))
    x = {r["vec_id"]: np.array(r["embedding"], float) for r in df.collect() if r["embedding"] is not None and len(r["embedding"]) == 64 and None not in r["embedding"]}
    x = {i: v for i, v in x.items() if np.isfinite(v).all() and v.any()}
    got = {}
    for r in vector_search.nearest(df, shard_rows=150).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == {i for i in x if i % 50 == 0}
    for q, found in got.items():
        score = vector_search.cosine(np.repeat(x[q][None], len(x), 0), np.array(list(x.values())))
        want = sorted((-s, i) for i, s in zip(x, score) if i != q)[:5]
        assert [(k + 1, i, -s) for k, (s, i) in enumerate(want)] == sorted(found)
    assert vector_search.nearest(df.limit(0)).count() == 0
    few = vector_search.nearest(given.where("vec_id in (0, 1, 2)"))
    assert few.count() == 2


def test_vector_search_of_repeated_ids_in_blocks(spark):
    rng = np.random.RandomState(8)
    x = [(int(i), rng.randn(4).tolist()) for i in range(300)] + [(50, rng.randn(4).tolist()), (50, [2.0, 0.0, 0.0, 0.0]), (7, [1.0, 0.0, 0.0, 0.0]), (7, [1.0, 0.0, 0.0, 0.0])]
    df = spark.createDataFrame(x, "vec_id long, embedding array<double>")
    got = {}
    for r in vector_search.nearest(df, shard_rows=60, block_rows=2).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    m = np.array([v for _, v in x])
    for q in {i for i, _ in x if i % 50 == 0}:
        own = [v for i, v in x if i == q]
        every = sorted((-s, i) for v in own for (i, _), s in zip(x, vector_search.cosine(np.repeat(np.array([v]), len(m), 0), m)) if i != q)
        assert [s for _, _, s in sorted(got[q])] == [-s for s, _ in every[:5]]


def test_vector_search_keeps_ties_of_scaled_copies(monkeypatch):
    rng = np.random.RandomState(4)
    v = rng.randn(16)
    x = [v * 2.0 ** (i % 20 - 10) for i in range(400)] + [v + 1e-9 * rng.randn(16) for _ in range(100)] + list(rng.randn(500, 16))
    order = rng.permutation(len(x))
    index = pd.DataFrame({"id": np.arange(len(x)), "v": [x[i].tolist() for i in order]})
    m = np.array(index["v"].tolist())
    for held in (1_000_000, 50):
        monkeypatch.setattr(vector_search, "HELD_ROWS", held, raising=False)
        got = vector_search.search_shard(index, index[index["id"] % 50 == 0], 5, 1.0, 32)
        for q in range(0, len(x), 50):
            score = vector_search.cosine(np.repeat(m[q][None], len(m), 0), m)
            want = sorted((-s, i) for i, s in enumerate(score) if i != q)[:5]
            assert [(-r.score, r.vec_id) for r in got[got["query_id"] == q].itertuples()] == want


def test_larger_factor_visits_less_and_still_finds():
    rng = np.random.RandomState(0)
    centres = rng.randn(20, 16)
    x = centres[rng.randint(0, 20, 4000)] + 0.2 * rng.randn(4000, 16)
    x /= np.linalg.norm(x, axis=1)[:, None]
    t = vector_search.Tree(x, 32)
    exact, _ = t.search(x[:100], 5, 1.0)
    visited = t.visited.sum()
    loose, _ = t.search(x[:100], 5, 2.0)
    assert t.visited.sum() < visited < 100 * len(x)
    assert np.mean([len(set(a) & set(b)) / 5 for a, b in zip(exact, loose)]) > 0.8
    d = np.argsort(-(x[:100] @ x.T), axis=1, kind="stable")[:, :5]
    assert (np.sort(exact, axis=1) == np.sort(d, axis=1)).all()


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    df, counts = docs, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = df
        df = corpus_pipeline.materialize(stage(spark, df, sf))
        assert df.columns == docs.columns, name
        assert set(r["doc_id"] for r in df.select("doc_id").collect()) <= set(r["doc_id"] for r in before.select("doc_id").collect())
        counts.append(df.count())
    assert counts[0] > counts[1] >= counts[2] > counts[3] > 0
    assert corpus_pipeline.run(spark, sf).count() >= counts[4]


def test_pipeline_on_odd_rows(spark, docs, empty, sf):
    import corpus_pipeline

    df = docs.where("doc_id >= 10000").unionByName(docs.limit(60)).unionByName(docs.limit(20))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        df = corpus_pipeline.materialize(stage(spark, df, sf))
        assert df.columns == docs.columns, name
    assert corpus_pipeline.STAGES[-1][1](spark, df, sf).count() >= df.count()
    df = empty
    for name, stage in corpus_pipeline.STAGES[:-1]:
        df = corpus_pipeline.materialize(stage(spark, df, sf))
        assert df.count() == 0 and df.columns == empty.columns, name
    assert corpus_pipeline.STAGES[-1][1](spark, df, sf).count() == 0


def test_repeated_rows_are_each_judged(spark, docs):
    rows = docs.limit(25).unionByName(docs.limit(25))
    for of in (token_count.count_tokens, license_scan.scan, quality_rules.judge, packing.pack):
        got = of(rows)
        keys = [c for c in got.columns if c in ("doc_id", "n_tokens", "n_words", "labels", "kept", "piece", "start", "ids_crc32")]
        counts = got.groupBy(*keys).count()
        assert counts.where("count % 2 <> 0").isEmpty() and got.count() >= 50


@pytest.mark.parametrize("looked_at", [20, 10**6])
def test_continuations_count_all_different_histories(spark, monkeypatch, looked_at):
    rng = random.Random(4)
    words = [f"x{chr(97 + i)}{chr(97 + j)}" for i in range(8) for j in range(8)]
    texts = [" ".join(rng.choices(words, k=rng.randint(0, 40))) for _ in range(80)] + [None, "", "lone", "the end"]
    monkeypatch.setattr(toxicity, "LOOKED_AT", looked_at)
    before = {}
    for t in texts:
        t = (t or "").split()
        for h, w in zip([None, *t], t):
            before.setdefault(w, set()).update({h} - {None})
    hashes = toxicity.Hashes()
    got = [(r["w"], r["s"]) for r in toxicity.continuations(spark.createDataFrame([(t,) for t in texts], "text string")).collect()]
    assert sorted(got) == sorted((hashes[w], 1 + len(b)) for w, b in before.items()) and max(s for _, s in got) > 20
    assert toxicity.continuations(spark.createDataFrame([], "text string")).count() == 0


def test_models_back_off_to_all_continuations(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "shared_counts", None)
    docs = spark.createDataFrame([(i, f"one two {'foul' if i % 2 else 'fair'} three four") for i in range(60)], "doc_id long, text string")
    got = toxicity.score(docs, docs.select("doc_id", (F.col("doc_id") % 2).cast("int").alias("toxic"))).collect()
    assert all(r["predicted"] == r["doc_id"] % 2 for r in got)


def test_pairs_go_by_common_histories_and_come_back():
    rng = np.random.default_rng(5)
    h, w = rng.integers(-(1 << 62), 1 << 62, 300)[rng.integers(0, 300, 5000)], rng.integers(-(1 << 62), 1 << 62, 40)[rng.integers(0, 40, 5000)]
    common = np.sort(np.unique(h)[::2])
    sent = [toxicity.packed_pairs(h, w, c) for c in (toxicity.NONE, common)]
    for rows, c in zip(sent, (toxicity.NONE, common), strict=True):
        back = [p for _, data in rows for p in zip(*(x.tolist() for x in toxicity.unpacked_pairs(data, c)), strict=True)]
        assert sorted(back) == sorted({*zip(h.tolist(), w.tolist(), strict=True)})
    assert sum(len(d) for _, d in sent[1]) < 0.75 * sum(len(d) for _, d in sent[0])


def test_evidence_of_many_texts_is_that_of_each():
    rng = np.random.default_rng(6)
    words, texts = np.unique(rng.integers(0, 1 << 40, 50)), []
    for n in (0, 1, 7, 0, 30, 2):
        texts.append(rng.choice(words, n))
    known = np.sort(np.unique(np.concatenate([toxicity.pair_keys(k) for k in texts if len(k) > 1]))[::2])
    model = toxicity.Model(words[::2], np.linspace(-3, 3, len(words[::2])).astype(np.float32), known, np.linspace(-2, 4, len(known)).astype(np.float32))
    got = model.evidence(texts, (0.0, 1.5))
    values = [dict(zip(k.tolist(), v.tolist(), strict=True)) for k, v in ((model.words, model.word_values), (model.pairs, model.pair_values))]
    for row, k in zip(got, texts, strict=True):
        found = [[values[0].get(x, 0) for x in k.tolist()], [values[1].get(x, 0) for x in (toxicity.pair_keys(k).tolist() if len(k) > 1 else [])]]
        assert row.tolist() == pytest.approx([sum(x for x in v if abs(x) > m) for m in (0.0, 1.5) for v in found])


def test_packing_keeps_frequent_words_when_its_table_is_full(monkeypatch):
    """A word that keeps coming is encoded once, however many rare words pass; the table stays within its bound."""
    e = packing.WordEncoder(packing.tokenizer_path("word_bpe_49k.json"), 20)
    rare = ["".join(chr(97 + int(d)) for d in f"{i:03d}") for i in range(400)]
    made, packed = [], packing._packed
    monkeypatch.setattr(packing, "_packed", lambda ids: made.append(1) or packed(ids))
    got = b""
    for w in rare:
        got += e.encode(f"frequent {w}")
        assert len(e) + len(e.older) <= 20
    assert len(made) == len(rare) + 1
    assert got == b"".join(e._library(f"frequent {w}") for w in rare)


def test_packing_cuts_words_as_the_library():
    e = packing.WordEncoder(packing.tokenizer_path("word_bpe_49k.json"))
    for text in ("don't'll 's'sx ''s a's1'2've", "I'M _'t__s a_b 'x'", "l'été's 'é é'd1² _é_'re", "'SÉ'LLß'''m", "漢字'sか'な"):
        assert e.encode(text) == e._library(text), text


def test_pairs_are_handed_on_in_little_memory(monkeypatch):
    """24 bytes a word at most: each was held several times over before."""
    import tracemalloc

    rng = np.random.default_rng(3)
    held, hashes, want = toxicity.Pairs(), toxicity.Hashes(), set()
    monkeypatch.setattr(toxicity, "HELD", 500)  # words are forgotten meanwhile
    texts = [" ".join("w" + "".join(chr(97 + int(d)) for d in str(x)) for x in rng.zipf(1.3, 1000) % 20_000) for _ in range(400)]
    for text in ["", "alone", None, *texts]:
        held.add(text)
        k = toxicity.keys_of(text, hashes).tolist()
        want.update(zip(k[:-1], k[1:]))
    tracemalloc.start()
    rows, begin = held.handed_on()
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    got = [p for _, data in rows for p in zip(*(x.tolist() for x in toxicity.unpacked_pairs(data)), strict=True)]
    assert len(got) == len(want) and set(got) == want
    assert sorted({hashes[t.split()[0]] for t in [*texts, "alone"]}) == sorted(k for _, d in begin for k in np.frombuffer(d, np.int64).tolist())
    assert most < 24 * 400_000 + 2_000_000 and not held.size and held.handed_on() == ([], [])


def test_batches_of_python_workers_are_bounded_in_bytes(spark):
    def run(batches):
        import pyarrow as pa

        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "b"])

    common.ship(spark)
    rows = spark.range(0, 4000, 1, 1).select(F.repeat(F.lit("ab "), 1500).alias("text")).mapInArrow(run, "n long, b long").collect()
    assert sum(r["n"] for r in rows) == 4000 and max(r["b"] for r in rows) < 5_000_000


def test_a_large_model_is_asked_by_many_texts_at_once(spark, monkeypatch):
    """A pair costs a few bytes where texts meet the model, not a row with a digest; evidence is that of the model on every worker."""
    rng = np.random.default_rng(8)
    words = np.array(["w" + "".join(chr(97 + int(d)) for d in str(x)) for x in range(3000)])
    texts = [" ".join(words[rng.zipf(1.3, n) % 3000]) for n in rng.integers(0, 300, 400)] + [None, "", "alone"]
    texts += texts[:20]
    rows = [(None, a) for a in range(0, 3000, 2)] + [(a, b) for a in range(60) for b in range(60) if a != b]
    hashes = toxicity.Hashes()
    model = spark.createDataFrame([(None if h is None else hashes[words[h]], hashes[words[w]], float(v)) for (h, w), v in zip(rows, rng.normal(0, 2, len(rows)))], "h long, w long, value double")
    docs = spark.createDataFrame(list(enumerate(texts)), "id long, __text string").repartition(3)
    monkeypatch.setattr(toxicity, "ASKED_AT", 2000)
    found = [sorted((r["id"], r["__n"], *(round(v, 4) for v in r["__e"])) for r in toxicity.Scorer(docs, model, n).evidence(docs, (0.5, 1.0)).collect()) for n in (10**6, 0)]
    assert found[0] == found[1] and len(found[0]) == len(texts)
    keys = [toxicity.keys_of(t, hashes) for t in texts]
    asked = toxicity.asked_of(keys, np.full(1 << 24, 255, np.uint8), 64)
    most = sum(len(set(k.tolist())) + len({*zip(k[:-1].tolist(), k[1:].tolist())}) for k in keys)
    assert sum(len(d) for _, d in asked) < 6 * most
    assert toxicity.asked_of(keys, np.zeros(1 << 24, np.uint8), 64) == []


def test_what_a_stage_shuffled_goes_when_it_is_written(spark):
    import os

    at = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    held = lambda: {f for top in at for _, _, names in os.walk(top) for f in names if f.startswith("shuffle_")}
    before = held()
    out = common.materialize(spark.range(10_000).groupBy((F.col("id") % 1000).alias("k")).count())
    left = lambda: {f for f in held() - before if not f.endswith(".index") and ".checksum" not in f}
    for _ in range(50):
        if not left():
            break
        time.sleep(0.1)
    assert not left() and spark.conf.get(common.CLEAN, None) in (None, "false") and out.count() == 1000


def test_pairs_that_were_seen_once_count(spark, monkeypatch):
    """Every pair of the labelled texts has its difference in the model that scores, as its formula says."""
    rng, made = random.Random(12), []
    words = [f"w{chr(97 + i)}{chr(97 + j)}" for i in range(6) for j in range(6)]
    texts = [rng.choices(words[:30] if i % 2 else words[6:], k=12) for i in range(80)]
    monkeypatch.setattr(toxicity, "Scorer", lambda docs, rows, n, real=toxicity.Scorer: made.append(rows) or real(docs, rows, n))
    docs = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(80)], "doc_id long, toxic int")
    toxicity.learned_from(docs, labels)
    kept = {r["doc_id"] for r in docs.where(~toxicity.held_out() & (F.pmod(F.xxhash64("doc_id"), F.lit(3)) != 2)).collect()}
    hashes, seen = toxicity.Hashes(), Counter(p for i in kept for p in zip(texts[i], texts[i][1:]))
    pairs = toxicity.materialize(toxicity.pair_counts(docs.where(F.col("doc_id").isin(sorted(kept))).select(F.col("text").alias("__text"), (F.col("doc_id") % 2).cast("int").alias("__toxic"))))
    every = {(r["h"], r["w"]) for r in toxicity.differences(pairs, toxicity.materialize(toxicity.continuations(docs)), seen=1).collect()}
    got = {(r["h"], r["w"]) for r in made[0].collect()}
    once = {(hashes[h], hashes[w]) for (h, w), n in seen.items() if n == 1}
    assert got == every and len(got & once) > 20
