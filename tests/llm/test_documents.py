"""Operators on documents against brute force, exact round trips, held-out accuracy, and awkward inputs."""

import hashlib
import random
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from motifscan.llm import bpe, common, flac, hashing, langid, licences, lines, mixing, neardup, repeats, sharding
from motifscan.llm.common import table
from motifscan.llm.components import connected_components
from motifscan.llm.queries import oracle_sql, queries
from tests.llm.conftest import WORD, rows_of

TOKENS = public_tokenizers.path("word_bpe_49k.json")


# FLAC


def padded(t):
    raw = (t or "").encode()
    return raw + b" " * (-len(raw) % 192 if raw else 192)


def test_flac_round_trip(spark, sf, odd_docs):
    for docs in (table(spark, sf, "documents"), odd_docs):
        for r, text in [(r, t) for r, t in zip(flac.to_media(docs, with_media=True).collect(), [x.text for x in docs.collect()], strict=True)]:
            want = padded(text)
            assert (r.n_bytes, r.payload_bytes) == (len((text or "").encode()), len(want))
            assert r.payload_sha256 == hashlib.sha256(want).hexdigest() and r.tail_crc32 == zlib.crc32(want[-16:])
            assert r.media_sha256 == hashlib.sha256(r.media).hexdigest() and r.media_bytes == len(r.media)


@pytest.mark.parametrize("lpc", [0, 1, 2, 4])
def test_both_flac_decoders(lpc):
    rng = np.random.default_rng(3)
    wave = (128 + 90 * np.sin(np.arange(192 * 9) / 7) + rng.normal(0, 3, 192 * 9)).clip(0, 255).astype(np.uint8).tobytes()
    for payload in (wave, bytes(192), b"\xff" * 384, rng.bytes(192 * 130), bytes(range(192)) * 2):
        stream = flac.encode_many([payload], lpc)[0]
        slow = [v for _, _, pcm in flac.decode_stream(stream) for v in pcm[0]]
        fast = flac.decode_many([stream])[0]
        assert slow == fast.tolist() and bytes((v + 128) & 255 for v in slow) == payload
        assert flac.read_samples(stream, 100, 150)[0] == slow[100:250]
        assert flac.read_samples(stream, len(payload) - 5, 50)[0] == slow[-5:]
    assert len(flac.encode_many([wave], 2)[0]) < len(wave)


def test_flac_frames_and_damage(spark):
    payload = bytes(range(192)) * 70
    stream = flac.encode_many([payload])[0]
    df = spark.createDataFrame([(1, stream), (2, None), (3, stream[:200] + b"!" + stream[201:])], "doc_id long, media binary")
    rows = flac.pcm_blocks(df).orderBy("doc_id", "block").collect()
    one = [r for r in rows if r.doc_id == 1]
    assert [r.sample_offset for r in one] == list(range(0, 192 * 70, 192))
    pcm = np.frombuffer(b"".join(bytes(r.pcm) for r in one), "<i4")
    assert ((pcm + 128) & 255).astype(np.uint8).tobytes() == payload
    assert not [r for r in rows if r.doc_id == 2] and any(r.error for r in rows if r.doc_id == 3)
    with pytest.raises(flac.Damaged):
        flac.decode_many([stream[:200] + b"!" + stream[201:]])


def test_flac_header_numbers():
    assert flac.coded_number(5) == b"\x05" and flac.coded_number(300) == chr(300).encode() and flac.coded_number(70_000) == chr(70_000).encode()


# BPE


def test_tokens_are_the_librarys(spark, sf, odd_docs):
    lib = Tokenizer.from_file(TOKENS)
    for docs in (table(spark, sf, "documents"), odd_docs):
        got = rows_of(bpe.encode_documents(docs, TOKENS))
        want = Counter()
        for r in docs.collect():
            ids = lib.encode(r.text or "", add_special_tokens=False).ids
            want[(r.doc_id, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest())] += 1
        assert got == want


def test_random_unicode_tokens():
    lib, own, rng = Tokenizer.from_file(TOKENS), bpe.WordBpe(TOKENS), random.Random(7)
    pool = [chr(c) for c in [*range(0, 0x250), *range(0x370, 0x400), 0x300, 0x301, 0x1F600, 0x200D, 0x2028, 0x3000, 0xAC00, 0x1100, 0x4E2D, 0x130]] + ["<|endoftext|>", "<|startoftext|>", "'s", "'LL", "x" * 70]
    for _ in range(3000):
        text = "".join(rng.choice(pool) for _ in range(rng.randint(0, 40)))
        assert own.encode(text) == lib.encode(text, add_special_tokens=False).ids


def test_decode_column(spark, odd_docs):
    enc = bpe.encode_documents(odd_docs, TOKENS, with_ids=True)
    got = {r.doc_id: r.decoded for r in bpe.decode_column(enc, TOKENS).collect()}
    assert all(got[r.doc_id] == r.decoded for r in enc.collect())


# sharding


@pytest.mark.parametrize("shards", [1, 7, 40])
def test_shards(spark, sf, odd_docs, shards):
    for docs in (table(spark, sf, "documents"), odd_docs):
        rows = sharding.shard_by_bytes(docs, shards).collect()
        assert Counter((r.doc_id, r.size, r.text_crc32) for r in rows) == Counter((d.doc_id, len((d.text or "").encode()) + 16, zlib.crc32((d.text or "").encode())) for d in docs.collect())
        total, most = sum(r.size for r in rows), max(r.size for r in rows)
        for s in range(shards):
            own = [r for r in rows if r.shard == s]
            assert sorted(r.slot for r in own) == list(range(len(own)))
            assert abs(sum(r.size for r in own) - total / shards) <= most
        assert {r.law for r in rows} == {"bytes"} and {r.grown_shard for r in rows} == {None}


# mixing


def targets(sizes):
    """Shares by weight with what is over 2 times a source's size shared again, one step after another."""
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    out, open_, left = {}, list(names), 1.5 * sum(sizes.values())
    while True:
        total = sum(weight[s] for s in open_)
        over = [s for s in open_ if left * weight[s] / total > 2 * sizes[s]]
        if not over:
            return out | {s: left * weight[s] / total for s in open_}
        for s in over:
            out[s] = 2.0 * sizes[s]
            open_.remove(s)
            left -= out[s]


def test_mix(spark, sf, odd_docs):
    for docs in (table(spark, sf, "documents"), odd_docs):
        d = docs.collect()
        size = Counter()
        for r in d:
            size[r.source] += len(WORD.findall(r.text or ""))
        want = targets(size)
        rows = mixing.plan_mix(docs, keep=(F.col("source").alias("own"),)).collect()
        assert len(rows) == len(d)
        for s, n in size.items():
            own = [r for r in rows if r.own == s]
            assert all(r.source_size == n and r.target == pytest.approx(want[s]) and 0 <= r.taken <= 2 * r.size for r in own)
            assert abs(sum(r.taken for r in own) - want[s]) <= max(r.size for r in own)
        again = mixing.plan_mix(docs.repartition(5), keep=(F.col("source").alias("own"),))
        assert rows_of(again) == Counter(map(tuple, rows))


def test_rounding_keeps_expectations(spark):
    """Each document is taken as often, on average, as its source's target over its size says; the words of each round are the target's."""
    size = np.array([1 + i % 9 for i in range(400)])
    docs = spark.createDataFrame([(i, "w " * int(n), "a" if i % 2 else "b") for i, n in enumerate(size)], "doc_id long, text string, source string").cache()
    copies = np.zeros((12, 400))
    for seed in range(12):
        for r in mixing.plan_mix(docs, seed=seed).collect():
            copies[seed, r.doc_id] = r.taken / r.size
    want = targets(Counter({"a": int(size[1::2].sum()), "b": int(size[::2].sum())}))
    assert (copies[:, 1::2] == 2).all() and want["a"] == 2 * size[1::2].sum()  # at its cap
    b, n = copies[:, ::2], size[::2]
    mean = want["b"] / n.sum()
    assert 0 < mean % 1 < 1 and set(np.unique(b)) <= {np.floor(mean), np.ceil(mean)}
    assert (np.abs((b * n).sum(1) - want["b"]) <= n.max()).all()
    spread = np.sqrt((mean % 1) * (1 - mean % 1))
    for k in range(1, 10):  # no size is favoured: within five standard deviations of independent draws
        own = b[:, n == k]
        assert abs(own.mean() - mean) <= 5 * spread / np.sqrt(own.size) + 1e-9


def test_mix_documents(spark, sf):
    docs = table(spark, sf, "documents")
    mixed = mixing.mix_documents(docs)
    assert mixed.columns == docs.columns
    got = Counter(r.doc_id for r in mixed.collect())
    assert got == Counter({r.doc_id: r.taken // r.size for r in mixing.plan_mix(docs, keep=(F.xxhash64(*docs.columns).alias("_row"),)).collect() if r.taken})


def test_languages_of_long_texts_and_empty_rows(spark):
    rows = [(i, "the of and with " * 4, "en") for i in range(1, 20)] + [(i, "." * 30 + "und die der nicht " * 30, "de") for i in range(20, 40)] + [(i, "...", "fr") for i in range(40, 400)] + [(i, "le la les dans ", "fr") for i in range(400, 403)]
    model = langid.learn(spark.createDataFrame(rows, "doc_id long, text string, lang string"), sample=10, longest=200)
    assert model.languages == ["de", "en", "fr"]
    assert [x[0] for x in langid.predict(model, ["und die der nicht", "the of and with", "le la les dans"])] == ["de", "en", "fr"]


def test_chains_know_their_neighbours():
    rng = np.random.default_rng(9)
    model = langid.Crf(["a", "b", "c"], np.zeros((1, 3)), np.zeros(0, np.uint64), np.zeros((0, 3)), np.eye(3) * 2, rng.normal(size=3))
    e, of = rng.normal(size=(300, 3)).astype(np.float32), np.repeat([0, 1, 2], [200, 30, 70])
    whole = np.concatenate([langid.marginals(model, e[of == i], np.zeros((of == i).sum(), np.int64), np.arange((of == i).sum()))[0] for i in range(3)])
    apart = langid.marginals(model, e, *langid._chains(of))[0]
    assert np.abs(langid.word_marginals(model, e, of) - whole).max() < 1e-3 < 0.05 < np.abs(apart - whole).max()


# lines


def test_short_lines_go_if_equal(spark):
    rows = [(1, "menu\nmenu\n目次目次目次目\nmemo\n \n "), (2, "menu\n目次目次目次目\nhome page\nhome pages\n ")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert {r.doc_id: r.removed for r in lines.dedup_report(df).collect()} == {1: "1", 2: "0,1,3"}
    assert {r.doc_id: r.removed for r in lines.dedup_report(df, near_chars=20).collect()} == {1: "1", 2: "0,1"}
    assert [r.text for r in lines.dedup_lines(df).orderBy("doc_id").collect()] == ["menu\n目次目次目次目\nmemo\n \n ", "home page\n "]


def near(a, b):
    if abs(len(a) - len(b)) > 1:
        return False
    i = 0
    while i < min(len(a), len(b)) and a[i] == b[i]:
        i += 1
    if len(a) == len(b):
        return a[i + 1 :] == b[i + 1 :]
    a, b = sorted((a, b), key=len)
    return a[i:] == b[i + 1 :]


def brute_lines(rows):
    every = [(d, i, x) for d, t in rows if t is not None for i, x in enumerate(t.split("\n")) if x.strip(" ")]
    out = {}
    for d, i, x in every:
        if any((e, j) < (d, i) and (x == y or min(len(x), len(y)) >= 8 and near(x, y)) for e, j, y in every):
            out.setdefault(d, []).append(i)
    return out


@pytest.mark.parametrize("frequent", [1 / 1000, 1 / 20])
def test_lines(spark, monkeypatch, frequent):
    monkeypatch.setattr(common, "FREQUENT", frequent)
    monkeypatch.setattr(common, "MANY", 3)
    rng, rows = random.Random(3), []
    base = ["".join(rng.choice("abé ") for _ in range(n)) for n in (2, 7, 8, 9, 15, 16, 17, 31, 32, 33, 47, 48, 81, 160, 161, 700, 2000)]
    for d in range(90):
        text = []
        for _ in range(rng.randint(0, 6)):
            x = rng.choice(base)
            for _ in range(rng.choice([0, 1, 1, 1, 2])):
                i, c = rng.randrange(len(x) + 1), rng.choice("abé ")
                x = rng.choice([x[:i] + c + x[i:], x[:i] + x[i + 1 :], x[:i] + c + x[i + 1 :]])
            text.append(x)
        rows.append((d, "\n".join(text)))
    rows += [(500, None), (501, ""), (502, "\n\n")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    want = brute_lines(rows)
    assert {r.doc_id: [int(x) for x in r.removed.split(",")] for r in lines.dedup_report(df).collect() if r.removed} == want
    for r in lines.dedup_lines(df).collect():
        text = dict(rows)[r.doc_id]
        assert r.text == (None if text is None else "\n".join(x for i, x in enumerate(text.split("\n")) if i not in want.get(r.doc_id, [])))


# near-duplicates


def brute_groups(rows, percent=85):
    def shingles(t):
        w = WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    sets = {d: shingles(t) for d, t in rows}
    up = {d: d for d in sets}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    holders = {}
    for d, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(d)
    for d, s in sets.items():
        for e, n in Counter(e for x in s for e in holders[x] if e < d).items():
            if 100 * n >= percent * (len(s) + len(sets[e]) - n):
                a, b = root(d), root(e)
                up[max(a, b)] = min(a, b)
    return {d: (len(sets[d]), root(d)) for d in sets}


@pytest.mark.parametrize("percent, blocks", [(80, None), (85, None), (85, (5, 4)), (80, (3, 7))])
def test_near_duplicates(spark, monkeypatch, percent, blocks):
    if blocks:  # so that these small groups take many blocks
        monkeypatch.setattr(neardup, "BUCKET_BLOCK", blocks[0])
        monkeypatch.setattr(neardup, "CLUSTER_BLOCK", blocks[1])
    rng = random.Random(5)
    voc = [f"w{i}" for i in range(3000)] + ["É"]
    base, rows = [[rng.choice(voc) for _ in range(n)] for n in (3, 5, 8, 40, 120, 300, 900)], []
    for d in range(400):
        w = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 2, 3, 5])):
            w[rng.randrange(len(w))] = rng.choice(voc)
        rows.append((d, " ".join(w) if rng.random() < 0.8 else "\n".join(x.upper() for x in w)))
    rows += [(900, None), (901, ""), (902, " ")]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), percent).collect()}
    assert got == brute_groups(rows, percent)


def test_signatures_estimate_similarity():
    rng = np.random.default_rng(1)
    for j in (0.3, 0.6, 0.85):
        errors = []
        for _ in range(40):
            common = int(800 * j)
            u = rng.integers(0, 1 << 63, 1600 - common, dtype=np.uint64)
            a, b = u[:800], np.concatenate([u[:common], u[800:]])
            low = neardup.minima(np.concatenate([a, b]), np.array([800, len(b)]))
            same = int(((low[:, 0] ^ low[:, 1]) & 15 == 0).sum())
            errors.append(neardup.similarity(same) - common / (800 + len(b) - common))
        assert abs(np.mean(errors)) < 0.03
    assert neardup.bands_for(0.85) == 20 and neardup.bands_for(0.8) == 28


def test_large_groups_are_counted_by_products():
    rng = np.random.default_rng(2)
    core = rng.integers(0, 1 << 62, 300, dtype=np.uint64)
    sets = [np.unique(np.concatenate([core[rng.random(300) > 0.05], rng.integers(0, 1 << 62, int(rng.integers(0, 30)), dtype=np.uint64)])) for _ in range(60)]
    groups = neardup.confirm(sets, 85)
    few = neardup.Groups(60)
    for i in range(60):
        for j in range(i):
            n = len(np.intersect1d(sets[i], sets[j]))
            if 100 * n >= 85 * (len(sets[i]) + len(sets[j]) - n):
                few.join(i, j)
    assert [groups.root(i) for i in range(60)] == [few.root(i) for i in range(60)]


# repeats


def brute_repeats(rows, k=35):
    words = {d: WORD.findall(t or "") for d, t in rows}
    windows = {d: [tuple(w[i : i + k]) for i in range(len(w) - k + 1)] for d, w in words.items()}
    count = Counter(x for ws in windows.values() for x in ws)
    out = {}
    for d, w in words.items():
        gone = {i + j for i, x in enumerate(windows[d]) if count[x] > 1 for j in range(k)}
        out[d] = (len(w), len(gone), hashlib.sha256(" ".join(x for i, x in enumerate(w) if i not in gone).encode()).hexdigest())
    return out


@pytest.mark.parametrize("rounds", [2, 4, 5])
def test_repeats(spark, rounds):
    rng, rows = random.Random(2), []
    voc = [f"w{i}" for i in range(50)]
    passages = [[rng.choice(voc) for _ in range(rng.choice([34, 35, 36, 50, 90]))] for _ in range(8)] + [["a"] * 60, ["a", "b"] * 40, ["a", "b", "c"] * 20]
    for d in range(200):
        w = []
        for _ in range(rng.randint(0, 4)):
            p = rng.choice(passages)
            i = rng.randrange(len(p))
            w += p if rng.random() < 0.4 else p[i : rng.randrange(i, len(p)) + 1] if rng.random() < 0.5 else [rng.choice(voc) for _ in range(rng.randint(0, 60))]
        rows.append((d, " ".join(w)))
    rows += [(900, None), (901, ""), (902, " "), (903, rows[5][1]), (904, "x " * 35), (905, "y " * 36)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    assert {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in repeats.dedup_substrings(df, rounds=rounds).collect()} == brute_repeats(rows)


def test_repeats_by_row(spark):
    """Rows that share or lack an id are cut each by its own text."""
    copy, own, other, late = (" ".join(f"{x}{i}" for i in range(60)) for x in "abcd")
    rows = [(1, copy), (2, copy), (2, own), (None, other), (None, "x " + copy), (None, None), (3, late), (3, late)]
    got = Counter((r.doc_id, r.n_words, r.n_removed) for r in repeats.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect())
    assert got == Counter([(1, 60, 60), (2, 60, 60), (2, 60, 0), (None, 60, 0), (None, 61, 60), (None, 0, 0), (3, 60, 60), (3, 60, 60)])


def test_frequent_passages_are_dealt_out(spark, monkeypatch):
    monkeypatch.setattr(common, "FREQUENT", 1 / 50)
    monkeypatch.setattr(common, "MANY", 3)
    rng = random.Random(8)
    hot = [f"h{i}" for i in range(40)]
    rows = [(d, " ".join([rng.choice("abc") for _ in range(d % 7)] + hot + [f"u{d}" for _ in range(d % 5)])) for d in range(300)] + [(d, " ".join(f"v{d}{i}" for i in range(50))) for d in range(300, 340)]
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_sha256) for r in repeats.dedup_substrings(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == brute_repeats(rows)


def thue_morse():
    """Two words whose bytes follow the sequence and its inverse: sums of powers modulo 2^64 can't tell them apart."""
    one = b"a"
    for _ in range(10):
        one += bytes(195 - c for c in one)
    return one.decode(), bytes(195 - c for c in one).decode()


def test_words_that_sums_of_powers_confuse(spark):
    one, two = thue_morse()
    assert len(one) == 1024 and one != two
    df = spark.createDataFrame([(1, one), (2, two)], "doc_id long, text string")
    assert {(r.doc_id, r.component_id) for r in neardup.near_duplicates(df).collect()} == {(1, 1), (2, 2)}
    words = [f"w{i}" for i in range(34)]
    df = spark.createDataFrame([(1, " ".join([*words, one])), (2, " ".join([*words, two]))], "doc_id long, text string")
    assert [r.n_removed for r in repeats.dedup_substrings(df).collect()] == [0, 0]
    # the same of sequences of words
    data = np.frombuffer(" ".join("cat" if c == "a" else "dog" for c in one + two).encode(), np.uint8)
    hashes = hashing.word_hashes(data, *hashing.word_spans(data))
    for powers in (hashing.WORDS, hashing.MORE):
        sums = hashing.stretch_sums(hashes, powers)
        a, b = hashing.stretch_hash(sums, np.array([0, 1024]), np.array([1024, 2048]), powers)
        assert a != b


def test_stretches_are_hashed_modulo_the_prime():
    rng = np.random.default_rng(12)
    a, b = (rng.integers(0, hashing.PRIME, 500, dtype=np.uint64) for _ in range(2))
    a[:2] = b[:2] = hashing.PRIME - 1
    assert [int(x) for x in hashing.times(a, b)] == [int(x) * int(y) % hashing.PRIME for x, y in zip(a, b, strict=True)]
    sums, total = hashing.stretch_sums(a, hashing.WORDS), 0
    for i, x in enumerate(a.tolist()):
        total = (total + x * pow(hashing.WORDS.base, i, hashing.PRIME)) % hashing.PRIME
    assert int(sums[-1]) == total


@pytest.mark.parametrize("frequent", [1 / 1000, 1 / 10])
def test_components(spark, monkeypatch, frequent):
    monkeypatch.setattr(common, "FREQUENT", frequent)
    monkeypatch.setattr(common, "MANY", 3)
    links = [(0, i) for i in range(1, 60)] + [(500, i) for i in range(200, 260)] + [(i, i + 1) for i in range(300, 340)] + [(7, 7), (900, 901), (901, 900)]
    up = list(range(1000))
    for _ in range(60):
        for a, b in links:
            up[a] = up[b] = min(up[a], up[b])
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long"), common.Stage(spark, "test")).collect()}
    assert got == {v: up[v] for a, b in links if a != b for v in (a, b)}


@pytest.mark.parametrize("few", [0, 1 << 17])
def test_components_by_rounds_and_in_one_task(spark, monkeypatch, few):
    from motifscan.llm import components

    monkeypatch.setattr(components, "FEW", few, raising=False)
    links = [(i, i + 7) for i in range(0, 700) if i % 70 < 60] + [(10_000, i) for i in range(9_000, 9_040)] + [(5, 5)]
    stage, puts = common.Stage(spark, "test"), []
    put = stage.put
    stage.put = lambda df: puts.append(1) or put(df)
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long"), stage).collect()}
    up = {n: n for x in links if x[0] != x[1] for n in x}
    for _ in up:
        for a, b in links:
            if a != b:
                up[a] = up[b] = min(up[a], up[b])
    assert got == up
    assert few == 0 or len(puts) == 2  # no rounds where few edges are there


# licences


def test_known_identifiers():
    assert licences.parse_expression("MIT").permissive and not licences.parse_expression("mitnfa OR mit-foo").permissive
    scan = lambda t: licences.scan(t, licences.automaton({licences.TAG: (licences.TAG, False)}))
    n, _, _, _, _, labels, score, _, _ = scan("SPDX-License-Identifier: Apache-2.0 OR madeup-9")
    assert labels == ["id:apache-2.0", "permissive", "unknown-id:madeup-9"] and 0 < score < scan("SPDX-License-Identifier: Apache-2.0 OR GPL-2.0-only")[6]


def test_own_phrases(spark, sf):
    """The method's own labels against a plain search for words."""
    import re

    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    extra = [(10**6 + i, x) for i, x in enumerate(["Released under the MIT License.", "the GNU General Public License, public domain", "cc by nc 4.0", None, "bsd licenses aren't the bsd  license"])]
    docs = table(spark, sf, "documents").select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    got = {r.doc_id: r for r in licences.scan_licences(docs, with_places=True).collect()}
    for d in docs.collect():
        w = word.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in d.text or ""))
        places = {(i, x) for p, x in (*licences.BASE.items(), *licences.NOTICES.items()) for k in [p.split()] for i in range(len(w)) if w[i : i + len(k)] == k}
        own = {x for x in filter(None, got[d.doc_id].labels.split(",")) if ":" not in x and x != "permissive"}
        assert {(p.word, p.label) for p in got[d.doc_id].places} == places and own == {x for _, x in places}


def test_base_phrases(spark, sf):
    docs = table(spark, sf, "documents")
    got = {r.doc_id: r for r in licences.scan_licences(docs).collect()}
    import re

    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    for d in docs.collect():
        w = word.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in d.text or ""))
        hits = [(i, x) for p, x in licences.BASE.items() for k in [p.split()] for i in range(len(w)) if w[i : i + len(k)] == k]
        r = got[d.doc_id]
        assert (r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) == (len(w), len(hits), min(hits, default=(None,))[0], max(hits, default=(None,))[0], ",".join(sorted({x for _, x in hits})))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1


@pytest.mark.parametrize(
    ("text", "ids", "permissive", "whole"),
    [
        ("MIT", ("mit",), True, True),
        ("MIT OR GPL-3.0", ("gpl-3.0", "mit"), True, True),
        ("MIT AND GPL-3.0", ("gpl-3.0", "mit"), False, True),
        ("GPL-2.0 OR MIT AND Apache-2.0", ("apache-2.0", "gpl-2.0", "mit"), True, True),
        ("(GPL-2.0 OR MIT) AND AGPL-3.0", ("agpl-3.0", "gpl-2.0", "mit"), False, True),
        ("GPL-2.0 WITH Classpath-exception-2.0", ("gpl-2.0+classpath-exception-2.0",), False, True),
        ("MIT */", ("mit",), True, False),
        ("MIT OR", ("mit",), True, False),
        ("(MIT", ("mit",), True, False),
        ("", (), False, False),
        ("AND", (), False, False),
    ],
)
def test_expressions(text, ids, permissive, whole):
    e = licences.parse_expression(text)
    assert (e.licences, e.permissive, e.whole) == (ids, permissive, whole)


# languages


def test_language_accuracy_on_held_out(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    model = langid.learn(docs, sample=60)
    got = langid.identify(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where("held_out and lang is not null and lang_pred <> 'und'").collect()
    assert len(got) > 200 and sum(r.lang_pred == r.lang for r in got) / len(got) > 0.98
    words = langid.label_words(model, "the and of that with und die der nicht")
    assert [x for _, x, _ in words][:3] == ["en"] * 3 and words[-1][1] == "de"


def test_language_sample_is_bounded(spark, monkeypatch):
    """Without ids, and with a text that most rows repeat, every language is learned from, and from no more than its share."""
    rows = [(None, "the of and with", "en")] * 500 + [(None, f"the of and with {'it' * (i % 9)} {i}", "en") for i in range(400)] + [(None, "und die der nicht", "de")] * 300 + [(None, "le la les dans", "fr")]
    seen = {}
    monkeypatch.setattr(langid, "fit", lambda texts, labels: seen.update(n=Counter(labels)))
    langid.learn(spark.createDataFrame(rows, "doc_id long, text string, lang string"), sample=50)
    assert set(seen["n"]) == {"en", "de", "fr"} and 20 <= seen["n"]["en"] <= 100 and seen["n"]["de"] == seen["n"]["fr"] == 1
    with pytest.raises(ValueError):
        langid.learn(spark.createDataFrame(rows, "doc_id long, text string, lang string"), languages=2)


def test_language_of_odd_texts(spark, odd_docs):
    got = Counter((r.doc_id, r.lang_pred == "und") for r in langid.identify(odd_docs, langid.learn(odd_docs)).collect())
    assert got[(1, True)] and got[(2, True)] and got[(3, True)] and got[(6, True)] and got[(0, False)]
    assert all(0 <= s <= 1 for _, s in langid.predict(langid.fit(["abc"], ["en"]), ["abc", None, "é" * 3]))
    assert langid.predict(langid.fit([], []), ["abc"]) == [("und", 0.0)]


def test_forward_backward_is_exact():
    rng = np.random.default_rng(6)
    e, model = rng.normal(size=(5, 3)), langid.Crf(["a", "b", "c"], np.zeros((1, 3)), np.zeros(0, np.uint64), np.zeros((0, 3)), rng.normal(size=(3, 3)), rng.normal(size=3))
    p, _, _ = langid.marginals(model, e.astype(np.float32), np.zeros(5, np.int64), np.arange(5))
    import itertools

    total = np.zeros((5, 3))
    for y in itertools.product(range(3), repeat=5):
        w = np.exp(model.begin[y[0]] + sum(e[i, y[i]] for i in range(5)) + sum(model.moves[y[i], y[i + 1]] for i in range(4)))
        for i in range(5):
            total[i, y[i]] += w
    assert np.allclose(p, total / total.sum(1, keepdims=True), atol=1e-5)


# all


def test_awkward_inputs(spark, odd_docs, empty_docs):
    n = odd_docs.count()
    ids = Counter(r.doc_id for r in odd_docs.collect())
    for f in (flac.to_media, lambda d: bpe.encode_documents(d, TOKENS), sharding.shard_by_bytes, licences.scan_licences, lambda d: langid.identify(d, langid.learn(d)), mixing.plan_mix, lines.dedup_report, neardup.near_duplicates, repeats.dedup_substrings):
        assert f(empty_docs).count() == 0
        out = f(odd_docs).collect()
        assert len(out) == n and Counter(r.doc_id for r in out) == ids
    for f in (lambda d: langid.drop_unidentified(d, langid.learn(d)), lines.dedup_lines, neardup.keep_one, mixing.mix_documents):
        assert f(odd_docs).columns == odd_docs.columns and f(empty_docs).count() == 0
        assert f(odd_docs).count() >= 1


def test_values_on_awkward_inputs(spark, odd_docs):
    rows = [(r.doc_id, r.text) for r in odd_docs.collect()]
    words = Counter((d, len(WORD.findall(t or ""))) for d, t in rows)
    assert Counter((r.doc_id, r.n_words) for r in repeats.dedup_substrings(odd_docs).collect()) == words
    assert Counter((r.doc_id, r.size) for r in mixing.plan_mix(odd_docs).collect()) == words
    near_ = {(r.doc_id, r.n_shingles, r.component_id, r.kept) for r in neardup.near_duplicates(odd_docs).collect()}
    assert {(0, 3, 0, True), (4, 3, 0, False), (1, 0, 1, True), (2, 0, 2, True), (3, 0, 3, True), (5, 1, 5, True), (6, 1, 6, True), (None, 1, None, True)} <= near_
    report = Counter((r.doc_id, r.n_lines, r.removed) for r in lines.dedup_report(odd_docs).collect())
    assert report[(1, 0, "")] == 1 and report[(2, 1, "")] == 1 and report[(4, 1, "0")] == 2 and report[(7, 2, "1")] == 1 and report[(None, 1, "")] == 1


def test_clashing_names(spark):
    """Columns of the input keep their values whatever they are called."""
    own = ["id_", "_id", "row_", "_row", "a_", "b_", "n_", "copies_", "copy_", "_copies", "_key", "_doc", "_removed", "removed_", "of_doc_", "doc_", "gone_", "gone_row_", "key", "part_", "parts_", "h", "at", "line"]
    rows = [(i, f"first line {i * 7919}\nsecond line of its own {i * i * 31}", "s", *(f"{c}{i}" for c in own)) for i in range(6)] + [(6, "first line 0\nthird line", "s", *(f"{c}6" for c in own))]
    df = spark.createDataFrame(rows, ["doc_id", "text", "source", *own])
    for f in (lines.dedup_lines, neardup.keep_one, mixing.mix_documents):
        out = f(df)
        assert out.columns == df.columns
        got = out.collect()
        assert got and all(r[c] == f"{c}{r.doc_id}" for r in got for c in own)


@pytest.mark.parametrize("name", ["op3_lines", "op8_recompression", "op10_minhash"])
def test_sql(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    con.sql(f"create view documents as select * from '{sf}/documents.parquet'")
    df, want = queries()[name](spark, sf), con.sql(oracle_sql()[name])
    cols = sorted(df.columns)
    assert cols == sorted(want.columns)
    key = lambda rows, names: Counter(tuple(r[names.index(c)] for c in cols) for r in rows)
    assert key([tuple(r) for r in df.collect()], df.columns) == key(want.fetchall(), want.columns)
