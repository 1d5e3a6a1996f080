"""The operators against brute force, exact round trips and planted cases."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash

from treepairs.llm import bpe_chunks, debruijn, decontaminate, exact_dedup, langid, near_copies, pii, sharding, simhash, suffix_dedup, token_counts
from treepairs.llm.queries import BYTE_VOCABULARY, SHARDS, WORD_VOCABULARY, vocabulary

SPACE = re.compile(r"[\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus(n=60, seed=1):
    rnd = random.Random(seed)
    vocab = ["".join(rnd.choice("abcdeé") for _ in range(rnd.randint(1, 6))) for _ in range(80)]
    common = " ".join(rnd.choice(vocab) for _ in range(40))
    texts = []
    for _ in range(n):
        words = [rnd.choice(vocab) for _ in range(rnd.randint(0, 120))]
        kind = rnd.random()
        if kind < 0.3 and texts:
            base = rnd.choice(texts).split(" ")
            for _ in range(rnd.randint(0, 2)):
                base[rnd.randrange(len(base))] = rnd.choice(vocab)
            texts.append(" ".join(base))
        elif kind < 0.6:
            at = rnd.randint(0, len(words))
            texts.append(" ".join([*words[:at], common, *words[at:]]))
        elif kind < 0.7:
            texts.append(("xy" * rnd.randint(60, 200)) + "  \n " + " ".join(words))
        else:
            texts.append("\t".join(words))
    return texts + ["", " ", "word", "a b c d", "a  b\nc d", "z" * 3000, "z" * 3000]


def frame(spark, texts, nulls=True):
    rows = [(3 * i + 1, t, "en", "s", len(t)) for i, t in enumerate(texts)]
    if nulls:
        rows += [(10_001, None, None, None, None), (10_002, None, None, None, None), (1, texts[0], "en", "s", 0)]
    random.Random(3).shuffle(rows)
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def texts():
    return corpus()


@pytest.fixture(scope="module")
def docs(spark, texts):
    return frame(spark, texts).cache()


@pytest.fixture(scope="module")
def rows(docs):
    return [(r.doc_id, r.text) for r in docs.collect()]


def covered(sequences, window):
    """doc: places covered by a window that also starts earlier."""
    first = {}
    for doc, seq in sorted(sequences.items()):
        for i in range(len(seq) - window + 1):
            first.setdefault(tuple(seq[i : i + window]), (doc, i))
    out = {}
    for doc, seq in sequences.items():
        gone = set()
        for i in range(len(seq) - window + 1):
            if first[tuple(seq[i : i + window])] != (doc, i):
                gone.update(range(i, i + window))
        out[doc] = gone
    return out


def test_suffix_dedup(docs, rows):
    seqs = {d: (t or "").encode() for d, t in rows}
    gone = covered(seqs, 100)
    got = suffix_dedup.remove_repeated_bytes(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        s = seqs[r.doc_id]
        kept = bytes(b for i, b in enumerate(s) if i not in gone[r.doc_id])
        spans = sum(1 for i in gone[r.doc_id] if i - 1 not in gone[r.doc_id])
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(s), len(gone[r.doc_id]), spans, hashlib.sha256(kept).hexdigest())
    assert sum(r.n_removed for r in got) > 1000


def test_suffix_sort_groups():
    text = np.frombuffer(b"abcabcabcabcx" * 20, np.uint8)
    at, group = suffix_dedup.sort_windows(text, np.arange(len(text) - 19), 20)
    raw = text.tobytes()
    by = defaultdict(set)
    for a, g in zip(at.tolist(), group.tolist(), strict=True):
        by[g].add(raw[a : a + 20])
    assert all(len(v) == 1 for v in by.values()) and len({*map(frozenset, by.values())}) == len(by)


def test_long_documents_are_cut_with_overlap(spark, monkeypatch):
    from treepairs.llm import spans

    rnd = random.Random(5)
    text = bytes(rnd.choice(b"abcdefgh ") for _ in range(3000))
    long = [text, text[500:2500], text[::-1]]
    powers = spans.Powers()
    monkeypatch.setattr(spans, "AT_ONCE", 400)
    found = [spans.records(*p, 100, 32, powers) for p in spans.pieces([1, 2, 3], (suffix_dedup.byte_symbols(t) for t in long), 100)]
    r = np.concatenate(found)
    windows = Counter((int(x["doc"]), int(x["start"]) + i) for x in r for i in range(int(x["n"])))
    assert windows == Counter((d + 1, i) for d, t in enumerate(long) for i in range(len(t) - 99))


def test_substring_dedup(docs, rows):
    seqs = {d: [w for w in SPACE.split(t or "") if w] for d, t in rows}
    gone = covered(seqs, 20)
    got = debruijn.remove_repeated_words(docs).collect()
    assert len(got) == len(rows)
    for r in got:
        s = seqs[r.doc_id]
        kept = " ".join(w for i, w in enumerate(s) if i not in gone[r.doc_id])
        assert (r.n_words, r.n_removed, r.kept_sha256) == (len(s), len(gone[r.doc_id]), hashlib.sha256(kept.encode()).hexdigest())
    assert sum(r.n_removed for r in got) > 200


@pytest.mark.parametrize("remove", [suffix_dedup.remove_repeated_bytes, debruijn.remove_repeated_words])
def test_buckets_rise_with_the_bytes_of_the_texts(spark, docs, remove, monkeypatch):
    from treepairs.llm import span_jobs

    few = {tuple(r) for r in remove(docs).collect()}
    width = span_jobs.shuffle_width(spark)
    assert span_jobs.dealing(docs, "text") == (2 * width, width)
    assert span_jobs.dealing(docs.limit(0), "text") == (2 * width, width)
    size = sum(len((r.text or "").encode()) for r in docs.collect())
    monkeypatch.setattr(span_jobs, "BUCKET_BYTES", size // 40)
    monkeypatch.setattr(span_jobs, "PACKED_BYTES", 5000)
    monkeypatch.setattr(suffix_dedup, "MOST_RANGES", 7)
    buckets, tasks = span_jobs.dealing(docs, "text")
    assert buckets >= 40 and tasks == -(-buckets // span_jobs.BUCKETS_A_TASK)
    assert {tuple(r) for r in remove(docs).collect()} == few


def brute_print(text, shingle):
    words = [w for w in SPACE.split("".join(c.lower() if c.isascii() else c for c in text or "")) if w]
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    hs = [xxhash.xxh64_intdigest(" ".join(words[i : i + shingle]).encode(), 42) for i in range(n)]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > n)


@pytest.mark.parametrize(("shingle", "radius", "blocks", "choose"), [(4, 4, 5, 1), (5, 6, 8, 2)])
def test_simhash_groups(docs, rows, shingle, radius, blocks, choose):
    prints = {d: brute_print(t, shingle) for d, t in rows}
    ids = sorted(prints)
    parent = {d: d for d in ids}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if (prints[a] ^ prints[b]).bit_count() <= radius:
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    got = simhash.near_groups(docs, shingle, radius, blocks, choose).collect()
    assert len(got) == len(rows)
    for r in got:
        assert r.fingerprint == f"{prints[r.doc_id]:016x}" and r.component_id == root(r.doc_id)


def five_words(text):
    words = [w for w in SPACE.split((text or "").lower()) if w]
    return {" ".join(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set()


def near_roots(texts):
    """id: smallest id that similarities of 0.8 or more lead to."""
    sets, low = {d: five_words(t) for d, t in texts.items()}, {d: d for d in texts}

    def root(x):
        while low[x] != x:
            x = low[x]
        return x

    for a in sorted(sets):
        for b in (b for b in sorted(sets) if b > a):
            if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                x, y = sorted((root(a), root(b)))
                low[y] = x
    return {d: root(d) for d in texts}


def copies_of_copies():
    rnd, texts = random.Random(11), {}
    for _ in range(25):
        base = [f"w{rnd.randrange(400)}" for _ in range(rnd.randint(60, 200))]
        for _ in range(rnd.choice([1, 2, 12])):
            words = list(base)
            for _ in range(rnd.choice([0, 1, 2, 6])):
                words[rnd.randrange(len(words))] = f"w{rnd.randrange(400)}"
            texts[len(texts)] = " ".join(words)
    return texts | {900: "Ab  c\nd", 901: "ab c d", 902: "ab c e", 903: "", 904: None, 905: " ", 906: "lone"}


@pytest.mark.parametrize("hot", [4096, 3])
def test_near_copies_against_all_pairs(spark, monkeypatch, hot):
    monkeypatch.setattr(near_copies, "_HOT", hot)
    monkeypatch.setattr(near_copies, "_PAIRS_OF_TEXT", 4 if hot > 3 else 0)
    texts = copies_of_copies()
    want = {d: r for d, r in near_roots(texts).items() if r != d}
    docs = spark.createDataFrame([(t, d, "clash") for d, t in texts.items()], "text string, doc_id long, component string")
    got = {r.doc_id: r.group for r in near_copies.copy_groups(docs).collect()}
    assert got == want and len(want) > 50
    assert {901, 904, 905} <= got.keys() and not {900, 902, 903, 906} & got.keys()
    kept = near_copies.keep_one_of_group(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == texts.keys() - got.keys()


def test_near_copies_of_short_texts_are_all_found(spark):
    """Fingerprints alone lose about a fifth of the pairs of an eight-word text and the same with one word added."""
    rnd = random.Random(5)
    texts = {}
    for i in range(150):
        size = 8 if i < 100 else rnd.randint(12, 90)
        words = [f"w{rnd.randrange(10**6)}" for _ in range(size)]
        texts[3 * i] = " ".join(words)
        texts[3 * i + 1] = " ".join([*words, "more"])
        texts[3 * i + 2] = " ".join(words[: size // 2] + ["other"] + words[size // 2 + 1 :])
    texts |= {1000 + i: f"the very same five words {i} of all these texts" for i in range(40)}
    roots = near_roots(texts)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: r.group for r in near_copies.copy_groups(docs).collect()}
    assert got == {d: r for d, r in roots.items() if r != d} and len(got) >= 150


def test_near_copies_repeated_and_null_ids(spark):
    text = " ".join(f"w{i}" for i in range(50))
    rows = [(5, text), (5, text), (7, text + " more"), (None, text), (None, None), (8, "x " * 200_000), (9, "x " * 200_001)]
    kept = near_copies.keep_one_of_group(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert Counter(r.doc_id for r in kept) == {5: 1, None: 2, 8: 1}


def test_repeated_ids_with_different_texts(spark):
    one, two, three = (" ".join(f"{c}{i}" for i in range(30)) for c in "abc")
    rows = [(1, one), (2, one), (2, two), (3, three), (3, three.replace(" ", "\t")), (4, two + " more"), (4, three + " more"), (4, "alone")]
    exact = exact_dedup.keep_first(spark.createDataFrame(rows, "doc_id long, text string").repartition(3))
    left = sorted((r.doc_id, " ".join(r.text.split())) for r in exact.collect())
    assert left == sorted([(1, one), (2, two), (3, three), (4, two + " more"), (4, three + " more"), (4, "alone")])
    assert [r.text for r in exact.filter("doc_id = 3").collect()] == [three.replace(" ", "\t")]
    near = near_copies.keep_one_of_group(exact)
    assert near.columns == ["doc_id", "text"] and sorted(r.doc_id for r in near.collect()) == [1, 2, 3, 4]
    assert [r.text for r in near.filter("doc_id = 4").collect()] == ["alone"]


def test_gray_groups_find_all_pairs():
    rnd = np.random.default_rng(1)
    base = rnd.integers(0, 1 << 63, 30, dtype=np.uint64)
    fp = np.unique(np.concatenate([base ^ (np.uint64(1) << rnd.integers(0, 64, 30, dtype=np.uint64)) for _ in range(40)]))
    fp = fp[np.argsort(simhash.gray_rank(fp))]
    got = {(int(a), int(b)) for i, j in simhash.group_links(fp, 4) for a, b in zip(i, j, strict=True)}
    want = {(i, j) for i in range(len(fp)) for j in range(i + 1, len(fp)) if (int(fp[i]) ^ int(fp[j])).bit_count() <= 4}
    assert got == want and want


@pytest.mark.parametrize("few", [0, 1 << 14])
def test_components_of_a_chain(spark, monkeypatch, few):
    from treepairs.llm import components as module
    from treepairs.llm.components import components

    monkeypatch.setattr(module, "FEW", few)

    n = 60
    got = {r.node: r.component for r in components(spark.createDataFrame([(i, i + 1) for i in range(n)] + [(1000, 1001)], "a long, b long")).collect()}
    assert got == {i: 0 for i in range(n + 1)} | {1000: 1000, 1001: 1000}


def test_exact_groups(docs, rows):
    norm = [(d, SPACE.sub(" ", t or "")) for d, t in rows]
    low, size = {}, Counter(t for _, t in norm)
    for d, t in norm:
        low[t] = min(low.get(t, d), d)
    want = Counter((d, low[t], size[t], d == low[t], hashlib.sha256(t.encode()).hexdigest()) for d, t in norm)
    assert Counter(map(tuple, exact_dedup.exact_groups(docs).collect())) == want
    assert Counter(map(tuple, exact_dedup.exact_groups(docs, bucket_bytes=300).collect())) == want
    kept = exact_dedup.keep_first(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == set(low.values()) and kept.count() == len(low)


def test_maglev_table():
    table = sharding.fill(SHARDS, 2039)
    share = Counter(table)
    assert set(share) == set(range(16)) and max(share.values()) - min(share.values()) <= 1
    fewer = sharding.fill(SHARDS[:-1], 2039)
    assert sum(a != b for a, b in zip(table, fewer, strict=True) if a != 15) < 0.25 * 2039
    with pytest.raises(ValueError):
        sharding.fill(SHARDS, 2040)


def test_place(spark, docs):
    from pyspark.sql import functions as F

    placed = sharding.place(docs.withColumn("slot", F.lit("clash")), F.col("doc_id"), SHARDS, 211)
    assert placed.count() == docs.count() and placed.groupBy("doc_id").agg(F.countDistinct("shard").alias("n")).filter("n > 1").isEmpty()
    plan = placed._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Python" not in plan


def test_token_counts_and_bpe(spark):
    from tokenizers import Tokenizer

    odd = ["a <|endoftext|> b<|endoftext|>c", "x\n\n y  z\t w", "é́ ñ 漢字 🙂🙂 a", " " * 3000, "don't we'll  I'm\r\n x", "\x1c a\x1d \x85 b", "<|startoftext|> hi", "ΑΣ Σ. İI", "ab " * 2000]
    cases = frame(spark, corpus(30, 7) + odd)
    want = {r.doc_id: r.text or "" for r in cases.collect()}
    w, b = (Tokenizer.from_file(vocabulary(v)) for v in (WORD_VOCABULARY, BYTE_VOCABULARY))
    for r in token_counts.count_tokens(cases, vocabulary(WORD_VOCABULARY)).collect():
        n = len(w.encode(want[r.doc_id], add_special_tokens=False).ids)
        assert (r.n_bytes, r.n_tokens, r.over_limit) == (len(want[r.doc_id].encode()), n, n > 2048)
    for r in bpe_chunks.encode(cases, vocabulary(BYTE_VOCABULARY)).collect():
        ids = b.encode(want[r.doc_id], add_special_tokens=False).ids
        assert r.ids == ids and r.n_tokens == len(ids) and r.decoded == b.decode(ids, skip_special_tokens=False) == want[r.doc_id]
    for r in bpe_chunks.encode_digest(cases, vocabulary(BYTE_VOCABULARY)).collect():
        ids = b.encode(want[r.doc_id], add_special_tokens=False).ids
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()


def test_bpe_chunks_are_encoded_once():
    encoder = bpe_chunks.ChunkEncoder(vocabulary(BYTE_VOCABULARY))
    rnd = random.Random(8)
    word = lambda: "".join(rnd.choice("abcdefghij") for _ in range(rnd.randint(2, 9)))
    passage = " ".join(word() for _ in range(800))
    texts = [" ".join(word() for _ in range(rnd.randint(0, 30))) + " " + passage + " " + word() for _ in range(40)]
    called = []
    inner = encoder._encode_new
    encoder._encode_new = lambda pieces: called.append(len(pieces)) or inner(pieces)
    got = [encoder.encode([t])[0] for t in texts]
    plain = encoder.library
    for t, (ids, back) in zip(texts, got, strict=True):
        want = plain.encode(t, add_special_tokens=False).ids
        assert np.frombuffer(ids, "<u4").tolist() == want and back == plain.decode(want, skip_special_tokens=False)
    assert encoder.reused > 0.7 * encoder.seen and max(called[1:]) < 400 < called[0]
    assert all(c is None or c.ids is not None and not c.units for c in encoder.chunks.values())


def test_token_batches_are_balanced_by_bytes():
    rnd = random.Random(2)
    pieces = ["é" * rnd.randint(1, 200) for _ in range(300)] + ["a" * 5000]
    groups = list(token_counts.balanced(pieces, 4000))
    sizes = [sum(len(p.encode()) for p in g) for g in groups]
    assert sorted(p for g in groups for p in g) == sorted(pieces) and sizes[0] == 5000
    assert max(sizes[1:]) <= 4000 and min(sizes[1:]) > 0.8 * max(sizes[1:]) and list(token_counts.balanced([], 10)) == []


def test_decontamination_candidates_come_from_the_index():
    """Most similar windows are found by their fingerprints; those beyond the radius by the count of shingles."""
    rnd = random.Random(6)
    items = [(i, " ".join(f"w{rnd.randrange(5000)}" for _ in range(rnd.choice([12, 30, 60])))) for i in range(60)]
    index, found, windows = decontaminate.Items(items), 0, 0
    for i, text in items:
        words = text.split()
        words[-1] = "changed" if len(words) > 12 else words[-1]
        around = [f"x{rnd.randrange(50)}" for _ in range(20)]
        whole = index.matches(around + words + around)
        near = decontaminate.Items.near
        alone = {k for k, (_, p) in whole.items() if k in near(index, int(decontaminate._pack(decontaminate._signs(decontaminate._rolled(np.array([index.vocabulary.get(w, -1) for w in (around + words + around)[p : p + len(words)]]), 5)).sum(axis=0, keepdims=True))[0]))}
        windows += len(whole)
        found += len(alone)
    assert windows >= 50 and found > 0.9 * windows


def test_bpe_tables_may_start_anew():
    small = bpe_chunks.ChunkEncoder(vocabulary(BYTE_VOCABULARY), units=50, chunks=5)
    big = bpe_chunks.ChunkEncoder(vocabulary(BYTE_VOCABULARY))
    t = corpus(20, 9)
    assert [x for i in range(0, len(t), 3) for x in small.encode(t[i : i + 3])] == big.encode(t)


def test_language(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = langid.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r.held_out]
    assert len(held) > 100 and sum(r.lang == r.lang_pred for r in held) / len(held) > 0.97
    assert all(0 <= r.score <= 1 for r in got)


def test_language_edge_cases(spark):
    odd = spark.createDataFrame([(1, None, "en"), (2, "123 !!", "en"), (3, "", None), (4, "the of and", "en")], "doc_id long, text string, lang string")
    got = {r.doc_id: (r.lang_pred, r.score) for r in langid.identify(odd).collect()}
    assert got[1] == got[2] == got[3] == ("und", 0.0)
    kept = langid.keep_identified(odd)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} <= {4}


def test_decontamination(spark):
    rnd = random.Random(2)
    vocab = [f"w{i}" for i in range(300)]
    items = [(i, " ".join(rnd.choice(vocab) for _ in range(n))) for i, n in enumerate([15, 30, 59, 3, 5, 40, 40])] + [(7, ""), (8, None)]
    texts = []
    for i in range(60):
        words = [rnd.choice(vocab) for _ in range(rnd.randint(0, 200))]
        if i % 2:
            part = items[i % 7][1].split()
            for _ in range(rnd.randint(0, 2)):
                part[rnd.randrange(len(part))] = "changed"
            at = rnd.randint(0, len(words))
            words[at:at] = part
        texts.append((i, " ".join(words).upper() if i % 3 == 0 else ", ".join(words)))
    texts += [(100, None), (101, "")]
    want = {}
    for item, text in items:
        iw = decontaminate.words_of(text)
        if not iw:
            continue
        k = min(5, len(iw))
        own = Counter(tuple(iw[i : i + k]) for i in range(len(iw) - k + 1))
        for doc, t in texts:
            dw = decontaminate.words_of(t)
            best = 0
            for s in range(len(dw) - len(iw) + 1):
                x = Counter(tuple(dw[s + i : s + i + k]) for i in range(len(iw) - k + 1))
                best = max(best, sum((x & own).values()) / sum((x | own).values()))
            if best >= 0.8:
                want[doc, item] = best
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    for size in (1 << 20, 100):
        got = {(r.doc_id, r.item_id): r.similarity for r in decontaminate.contaminated(docs, bench, size).collect()}
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-12 for k in got)
    clean = {r.doc_id for r in decontaminate.keep_clean(docs, bench, 100).collect()}
    assert clean == {d for d, _ in texts} - {d for d, _ in want}
    assert decontaminate.contaminated(docs, bench.limit(0)).count() == 0


def test_decontamination_of_items_cut_short(spark):
    words = [f"w{i}" for i in range(40)]
    item = decontaminate.Items([(1, " ".join(words))])
    for size in range(1, 41):
        shared = max(0, size - 4)
        want = {0: (shared / 36, 0)} if shared / 36 >= 0.8 else {}
        for text in (words[:size], words[40 - size :]):
            assert item.matches(text) == want
    assert item.matches(words[:38] + ["other"])[0] == (34 / 37, 0)
    docs = spark.createDataFrame([(1, " ".join(words[:39])), (2, " ".join(words[:20]))], "doc_id long, text string")
    bench = spark.createDataFrame([(1, " ".join(words))], "item_id long, text string")
    assert [r.doc_id for r in decontaminate.keep_clean(docs, bench).collect()] == [2]


def test_pii(spark):
    texts = [
        (1, "mail Jo.77@mail0.example.com and jo.77@mail0.example.com, call +1 (578) 555-6437 or +1 578 555 6437."),
        (2, 'card 4111111111111111, 4918187128635271; ip 10.20.255.1 TOKEN = "9233A8ECF7C5B09FE5949719B6B82BC439E9329B"'),
        (3, 'token = "9233a8ecf7c5b09fe5949719b6b82bc439e9329b" Frau Anna Schmidt met Herr Schmidt; Mr. Smith'),
        (4, "version 3.0, nothing here 12345"), (5, None), (6, ""), (None, "a@b.example.org"), (7, "1.2.3.4 5.6.7.8"), (7, "1.2.3.4 5.6.7.8"),
        (8, " ".join(f"{a}.{b}.1.1" for a in range(1, 10) for b in range(1, 10))),
    ]
    docs = spark.createDataFrame(texts, "doc_id long, text string").withColumn("kind", __import__("pyspark").sql.functions.lit("clash"))
    out = pii.replace_entities(docs, "k")
    got = defaultdict(list)
    for r in out.collect():
        got[r.doc_id].append(r)
    assert out.columns == ["doc_id", "text", "kind", "n_entities"] and sum(map(len, got.values())) == len(texts)
    one = got[1][0]
    m = re.fullmatch(r"mail (\S+@mail0.example.com) and (\S+@mail0.example.com), call \+1 \((\d{3})\) (\d{3})-(\d{4}) or \+1 (\d{3}) (\d{3}) (\d{4})\.", one.text)
    assert m and m[1] == m[2] and "jo.77" not in one.text.lower() and m.groups()[2:5] == m.groups()[5:8] and one.n_entities == 4
    cards = re.search(r"card (\d{16}), (\d{16}); ip (\d\d\.\d\d\.\d{3}\.\d) TOKEN = \"([0-9A-F]{40})\"", got[2][0].text)
    luhn = lambda s: sum(int(c) if i % 2 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(s)) % 10 == 0
    assert cards and luhn(cards[1]) and cards[1] != "4111111111111111"
    names = re.search(r'token = "([0-9a-f]{40})" Frau (\w+na) (\w+) met Herr (\w+); Mr\. (\w+)', got[3][0].text)
    assert names and names[1] == cards[4].lower() and "Schmidt" not in got[3][0].text and names[3] == names[4] != names[5]
    assert got[4][0].text == texts[3][1] and got[4][0].n_entities == 0 and got[5][0].text is None and got[6][0].text == ""
    assert got[7][0].text == got[7][1].text != "1.2.3.4 5.6.7.8"
    many = got[8][0].text.split(" ")
    assert len(set(many)) == 81 and not set(many) & set(texts[-1][1].split(" "))
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Pandas" not in plan


def iban_ok(number):
    turned = number[4:] + number[:4]
    return int("".join(str(int(c, 36)) for c in turned)) % 97 == 1


def test_pii_names_phones_scripts_and_check_digits(spark):
    texts = [
        "Dr. John Smith met Anna Schmidt; Mr Lee. Contact MR. BOB BROWN. Smith left, so did Lee, BROWN and Mrs Mary Lee. smith is a trade",
        "письмо иван.петров@mail.ru; Госпожа Анна Петрова и Петрова",
        "DE89370400440532013000 and DE89 3704 0044 0532 0130 00, GB00WEST12345698765432",
        "(555) 123-4567, +1 555 123 4567, 555-123-4567",
    ]
    docs = spark.createDataFrame([(None, t, 1, 2, "x") for t in texts], "doc_id long, text string, surrogates int, digest int, pattern string")
    out = pii.replace_entities(docs, "k")
    assert out.columns == [*docs.columns, "n_entities"]
    one, two, three, four = sorted((r.text for r in out.collect()), key=lambda t: ["Dr", "пи", "DE", "(" + t[1:2]].index(t[:2]))
    m = re.fullmatch(r"Dr\. (\w+) (\w+) met (\w+) (\w+); Mr (\w+)\. Contact MR\. ([A-Z]+) ([A-Z]+)\. (\w+) left, so did (\w+), ([A-Z]+) and Mrs (\w+na) (\w+)\. smith is a trade", one)
    assert m and m[2] == m[8] and m[5] == m[9] == m[12] and m[7] == m[10]
    assert not {"John", "Smith", "Anna", "Schmidt", "Lee", "BOB", "BROWN", "Mary"} & set(m.groups()) and len({m[i].lower() for i in (1, 2, 3, 4, 5, 6, 7, 11)}) == 8
    mail = re.fullmatch(r"письмо ([а-я]{4}\.[а-я]{6})@mail\.ru; Госпожа ([А-Я][а-я]+на) ([А-Я][а-я]+) и ([А-Я][а-я]+)", two)
    assert mail and mail[1] != "иван.петров" and mail[3] == mail[4] != "Петрова"
    ibans = re.fullmatch(r"(DE\d{20}) and (DE\d\d(?: \d{4}){4} \d\d), (GB\d\d[A-Z]{4}\d{14})", three)
    assert ibans and ibans[2].replace(" ", "") == ibans[1] != "DE89370400440532013000" and iban_ok(ibans[1]) and not iban_ok("GB00WEST12345698765432")
    phones = re.fullmatch(r"\((\d{3})\) (\d{3})-(\d{4}), \+1 (\d{3}) (\d{3}) (\d{4}), (\d{3})-(\d{3})-(\d{4})", four)
    assert phones and phones.groups()[:3] == phones.groups()[3:6] == phones.groups()[6:] != ("555", "123", "4567")


def test_pii_against_plain_patterns(spark):
    """What plain patterns find in the given documents is gone, in the same places and formats; equal strings stay equal."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    plain = re.compile(r"[\w.%+-]+@[\w-]+(?:\.[\w-]+)+|(?<![\d.])\d{1,3}(?:\.\d{1,3}){3}(?![\d.])|\+\d \(\d{3}\) \d{3}-\d{4}")
    was = {r.doc_id: r.text or "" for r in docs.collect()}
    to, back, touched = {}, {}, 0
    for r in pii.replace_entities(docs, "k").collect():
        a, b = plain.findall(was[r.doc_id]), plain.findall(r.text or "")
        assert len(a) == len(b) and (r.n_entities > 0 or r.text == was[r.doc_id])
        touched += len(a) > 0
        for x, y in zip(a, b, strict=True):
            assert x != y and re.sub(r"[\w]", "", x) == re.sub(r"[\w]", "", y) and x.partition("@")[2] == y.partition("@")[2]
            assert to.setdefault(x.lower(), y.lower()) == y.lower() and back.setdefault(y.lower(), x.lower()) == x.lower()
    assert touched > 20 and not set(to) & set(back)


def plain_language(train, texts):
    """Predictions by the definition, without tables, bounds or batches."""
    words, langs = defaultdict(Counter), sorted({g for _, g in train})
    letters = lambda t: re.findall(r"[^\W\d_]+", (t or "").lower())
    for text, lang in train:
        words[lang].update(letters(text))
    counts = {lang: {0: words[lang]} for lang in langs}
    for lang in langs:
        for order in langid.ORDERS:
            counts[lang][order] = Counter()
            for w, n in words[lang].items():
                for g in langid.grams(w, order):
                    counts[lang][order][g] += n
    size = {(lang, o): sum(c.values()) for lang in langs for o, c in counts[lang].items()}
    log = lambda o, x: np.array([np.log((counts[lang][o][x] + 0.1) / (size[lang, o] + 1000.0)) for lang in langs])
    known = lambda o, x: any(x in counts[lang][o] for lang in langs)

    def word(w):
        if known(0, w):
            return log(0, w)
        for o in langid.ORDERS:
            seen = [log(o, g) for g in langid.grams(w, o) if known(o, g)]
            if seen:
                return sum(seen) / len(seen)
        return np.zeros(len(langs))

    out = []
    for t in texts:
        ws = letters(t)
        total = sum(word(w) - word(w).max() for w in ws) / max(1.0, len(ws) ** 0.5) if ws else None
        out.append(("und", 0.0) if total is None else (langs[int(total.argmax())], float(np.exp(total - total.max()).max() / np.exp(total - total.max()).sum())))
    return out


def test_language_against_plain_scores(spark):
    rnd = random.Random(4)
    stems = {"aa": "kal mer tol sin", "bb": "ruk pol vin dar", "cc": "été mär über ñon"}
    rows = []
    for i in range(120):
        lang = rnd.choice(list(stems))
        rows.append((i, " ".join("".join(rnd.choice(stems[lang].split()) for _ in range(rnd.randint(1, 3))) for _ in range(rnd.randint(0, 12))), lang))
    rows += [(500, "kal " * 50_000, None), (501, "ruk kal", None), (None, "mer tol", "aa"), (501, "ruk kal", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("score", __import__("pyspark").sql.functions.lit("clash"))
    got = Counter((r.doc_id, r.held_out, r.lang_pred, round(r.score, 4)) for r in langid.identify(docs).collect())
    import zlib

    out = lambda d: d is not None and zlib.crc32(str(d).encode()) % 4 == 2
    train = [(t, g) for d, t, g in rows if d is not None and g is not None and not out(d)]
    want = plain_language(train, [t for _, t, _ in rows])
    assert got == Counter((d, out(d), p, round(s, 4)) for (d, _, _), (p, s) in zip(rows, want, strict=True))


def test_language_needs_a_letter(spark):
    odd = ["½ ² Ⅻ", "123", "٣٤", "_ _", "①②", "a"]
    rows = [(i, t, "en") for i, t in enumerate(odd)] + [(100 + i, "the of and", "en") for i in range(8)]
    got = {r.doc_id: r.lang_pred for r in langid.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()}
    assert [got[i] for i in range(6)] == ["und"] * 5 + ["en"]


def test_any_long_may_be_an_id_and_any_name_a_column(spark):
    low = -(1 << 63)
    rows = [(low, "a b", 1, 2, 3), (5, "a  b", 1, 2, 3), (None, "a b", 1, 2, 3), (None, "c", 1, 2, 3), (0, "d" * 300_000, 1, 2, 3)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __nth int, digest int, nth int")
    got = Counter((r.doc_id, r.keep_id, r.group_size, r.kept) for r in exact_dedup.exact_groups(docs, bucket_bytes=300).collect())
    assert got == {(low, low, 3, True): 1, (5, low, 3, False): 1, (None, low, 3, False): 1, (None, None, 1, True): 1, (0, 0, 1, True): 1}
    for kept in (exact_dedup.keep_first(docs), near_copies.keep_one_of_group(docs)):
        assert kept.columns == docs.columns and sorted((r.doc_id is not None, r.doc_id or 0) for r in kept.collect()) == [(False, 0), (False, 0), (True, low), (True, 0)]


def test_empty_tables(spark):
    empty = spark.createDataFrame([], SCHEMA)
    bench = spark.createDataFrame([], "item_id long, text string")
    outs = [
        suffix_dedup.remove_repeated_bytes(empty), debruijn.remove_repeated_words(empty), simhash.near_groups(empty), exact_dedup.exact_groups(empty),
        exact_dedup.keep_first(empty), near_copies.keep_one_of_group(empty), langid.identify(empty), langid.keep_identified(empty), pii.replace_entities(empty, "k"),
        token_counts.count_tokens(empty, vocabulary(WORD_VOCABULARY)), bpe_chunks.encode_digest(empty, vocabulary(BYTE_VOCABULARY)),
        decontaminate.contaminated(empty, bench), decontaminate.keep_clean(empty, bench), sharding.place(empty, empty.doc_id, SHARDS),
    ]
    assert all(o.count() == 0 for o in outs)


def test_pipeline(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language ID", "exact dedup", "SimHash near-dedup", "benchmark decontamination", "BPE encoding"]
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, sf)
        assert after.columns == docs.columns, name
        assert after.join(before, "doc_id", "left_anti").isEmpty() and after.count() <= before.count()
        before = spark.createDataFrame(after.collect(), docs.schema)
    left = {r.doc_id for r in corpus_pipeline.run(spark, sf).collect()}
    assert left == {r.doc_id for r in before.collect()} and len(left) > 100
