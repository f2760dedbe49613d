"""Each operator on odd rows, on empty tables, and against brute force."""

import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pytest

from rankflow.llm import fingerprints, flac, licences, mixing, neardup, pieces, quality, queries, sharding, tokenfile, toxicity

OPERATORS = {
    "mix": lambda d, lab: mixing.words_taken(d),
    "mixed rows": lambda d, lab: mixing.mixed_documents(d),
    "quality": lambda d, lab: quality.resample(d, lab),
    "good": lambda d, lab: quality.good_documents(d, lab),
    "search": lambda d, lab: fingerprints.near_fingerprints(d),
    "simhash": lambda d, lab: fingerprints.edited_pairs(d),
    "near": lambda d, lab: neardup.near_components(d),
    "one of each": lambda d, lab: neardup.one_of_each_group(d),
    "toxic": lambda d, lab: toxicity.toxicity(d, lab),
    "clean": lambda d, lab: toxicity.clean_documents(d, d, lab),
    "tokens": lambda d, lab: tokenfile.token_file_digests(d, queries.BYTE_BPE),
    "pieces": lambda d, lab: pieces.piece_digests(d, queries.PIECE_BPE),
    "licences": lambda d, lab: licences.scan(d),
    "shards": lambda d, lab: sharding.assign_shards(d),
    "media": lambda d, lab: flac.media_digests(flac.encode_column(d)),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_odd_rows_and_empty_tables(odd, none, labels, name):
    run = OPERATORS[name]
    got = run(odd, labels).collect()
    if name not in ("mixed rows", "good", "one of each", "clean"):
        assert len(got) == odd.count()
    assert run(none, labels).count() == 0
    unlabelled = run(odd, labels.limit(0)).count()
    # without labels nothing is toxic, and all that the models know nothing about is good
    assert unlabelled == (len(got) if name not in ("good", "clean") else odd.count())


@pytest.mark.parametrize("name", ["mixed rows", "good", "one of each", "clean"])
def test_stages_keep_columns_of_any_name(odd, labels, name):
    got = OPERATORS[name](odd, labels)
    assert got.columns == odd.columns and all(r["_id"] == "clash" for r in got.collect())


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def test_mix_takes_near_target_and_never_too_often(spark):
    rng = random.Random(1)
    rows = [(i, " ".join("w" * rng.randint(1, 5) for _ in range(rng.randint(0, 300))), rng.choice(["a", "a", "a", "b", "c", "d", None])) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: r for r in mixing.words_taken(df).collect()}
    source = {i: s for i, _, s in rows}
    for s in set(source.values()):
        mine = [got[i] for i in got if source[i] == s]
        assert sum(r.taken for r in mine) == pytest.approx(mine[0].target, rel=0.01, abs=2)
        assert mine[0].source_size == sum(r.size for r in mine)
    assert all(0 <= r.taken <= 3 * r.size for r in got.values())
    targets = {s: next(got[i].target for i in got if source[i] == s) for s in set(source.values())}
    assert sum(targets.values()) == pytest.approx(sum(r.size for r in got.values()))
    again = {r.doc_id: r for r in mixing.words_taken(df.repartition(7)).collect()}
    assert again == got


def test_mix_of_small_sources(spark):
    rows = [(1, "a b c d", "x"), (2, "a b c d e f g h i j", "y")]
    got = mixing.words_taken(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert {r.doc_id: r.target for r in got} == {1: 10.0, 2: 4.0}
    assert all(abs(r.taken - r.target) <= 1 for r in got)


def test_mixed_rows_stay_near_the_targets(spark):
    rng = random.Random(3)
    rows = [(i, " ".join(["w"] * rng.randint(1, 90)), rng.choice("aabcd")) for i in range(500)] + [(i, None, "a") for i in range(500, 505)]
    rows += [(7, "other text of a repeated id", "b"), (7, "other text of a repeated id", "b")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    target = {r.sid: r.target for r in mixing.plan_mix(df)[1].collect()}
    got = {}
    for r in mixing.mixed_documents(df).collect():
        got[r.source] = got.get(r.source, 0) + len(r.text.split())
    for sid, source in enumerate("abcd"):  # half a document, and the rounding of slots
        assert abs(got[source] - target[sid]) <= 90 / 2 + 2


def test_mix_prefixes_follow_the_weights(spark):
    rows = [(i, " ".join(["w"] * 100), "abc"[i % 3]) for i in range(300)]
    _, targets, parts = mixing.plan_mix(spark.createDataFrame(rows, "doc_id long, text string, source string"))
    share = {r.sid: r.target / r.total for r in targets.collect()}
    slots = sorted({(r.slot, r.sid) for r in parts.collect()})
    for n in (50, 200, 800):
        for sid, part in share.items():
            assert abs(sum(s == sid for _, s in slots[:n]) - n * part) < 6


def test_mixed_rows_repeat_whole_documents(spark):
    rows = [(i, "a b c d", "abcd"[i % 4]) for i in range(80)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mixed_documents(df)
    assert got.columns == df.columns and 60 <= got.count() <= 100


def shingle_sets(rows):
    out = {}
    for i, t in rows:
        w = words(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        out[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    return out


def near_rows():
    rng = random.Random(5)
    vocabulary = [f"v{i}" for i in range(3000)]
    base = [rng.choice(vocabulary) for _ in range(120)]
    texts = []
    for k in range(120):  # a large group of near copies, some far apart
        w = list(base)
        for _ in range(rng.randint(0, 6)):
            w[rng.randrange(len(w))] = rng.choice(vocabulary)
        texts.append(" ".join(w))
    texts += texts[:15] + ["A b c", "a B c", "a b", "", None]
    texts += [" ".join(rng.choice(vocabulary) for _ in range(60)) for _ in range(40)]
    rng.shuffle(texts)
    return list(enumerate(texts))


@pytest.mark.parametrize("small,block", [(24, 400_000), (2, 400_000), (2, 1_000), (0, 300)])
def test_near_duplicates_equal_brute_force(spark, monkeypatch, small, block):
    monkeypatch.setattr(neardup, "SMALL", small)
    monkeypatch.setattr(neardup, "BLOCK_SHINGLES", block)
    rows = near_rows()
    sets = shingle_sets(rows)
    top = {i: i for i in sets}

    def find(x):
        while top[x] != x:
            x = top[x]
        return x

    for a, b in itertools.combinations(sets, 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= 85 * len(sets[a] | sets[b]):
            p, q = find(a), find(b)
            top[max(p, q)] = min(p, q)
    got = neardup.near_components(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    for r in got:
        assert (r.n_shingles, r.component_id, r.kept) == (len(sets[r.doc_id]), find(r.doc_id), r.doc_id == find(r.doc_id))


def test_components_of_paths_and_stars(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 130)] + [(200, 201), (201, 200)]
    got = {r.vertex: r.component for r in neardup.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and all(got[i] == 100 for i in range(100, 130)) and got[201] == 200


def test_equal_texts_have_equal_fingerprints_and_edits_show(spark):
    rng = random.Random(2)
    texts = [" ".join(f"w{rng.randrange(5000)}" for _ in range(200)) for _ in range(60)]
    rows = [(i, t) for i, t in enumerate(texts + texts[:3])]
    got = {r.doc_id: r for r in fingerprints.edited_pairs(spark.createDataFrame(rows, "doc_id long, text string"), rows_per_chunk=7).collect()}
    ids = sorted(got)
    for k, i in enumerate(ids):
        text, other = rows[i][1], rows[ids[k - 1]][1]  # the next in descending order
        edited = text[: len(text) - len(text) // 2] + other[: len(text) // 2]
        assert got[i].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        assert got[i].fingerprint == f"{fingerprints.fingerprint(text):016x}"
        assert got[i].near_next == fingerprints.likeness(int(got[i].fingerprint, 16), int(got[ids[k - 1]].fingerprint, 16))
    assert got[0].fingerprint == got[60].fingerprint
    assert np.mean([r.near_edited for r in got.values()]) > np.mean([r.near_next for r in got.values()]) + 0.1


def test_fingerprint_equals_a_vote_by_hand():
    import xxhash

    mask = (1 << 64) - 1
    for text in ["", "one", "one two", "a b c", "The quick brown fox jumps over the lazy dog " * 40]:
        h = [xxhash.xxh3_64_intdigest(w.encode()) for w in text.split()]
        width = min(3, len(h))
        votes = [0] * 64
        for i in range(len(h) - width + 1 if h else 0):
            t = width
            for x in h[i : i + width]:
                t = (t ^ x) * 0x9E3779B97F4A7C15 & mask
                t ^= t >> 32
            for byte in range(8):  # bits of the hash's bytes, most significant first
                for bit in range(8):
                    votes[8 * byte + bit] += 1 if t >> 8 * byte & 128 >> bit else -1
        want = sum((v > 0) << (8 * (k // 8) + 7 - k % 8) for k, v in enumerate(votes))
        assert fingerprints.fingerprint(text) == want


def test_search_counts_links_of_classes(spark):
    rng = random.Random(4)
    texts = [" ".join(f"w{rng.randrange(900)}" for _ in range(300)) for _ in range(30)]
    texts += [t.replace("w1 ", "v1 ", 1) for t in texts] + texts[:5] + ["", None]
    rows = list(enumerate(texts))
    prints = {i: fingerprints.fingerprint(t) for i, t in rows}
    first = {}
    for i, p in prints.items():
        first.setdefault(p, i)
    got = fingerprints.near_fingerprints(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r.doc_id: (r.class_id, r.n_links) for r in got} == {i: (first[p], sum(0 < (p ^ q).bit_count() <= 3 for q in first)) for i, p in prints.items()}


@pytest.mark.parametrize("few", [fingerprints.FEW_UNDER_KEY, 2, 1])
def test_block_tables_find_all_within_the_radius(spark, few):
    rng = random.Random(3)
    base = [rng.getrandbits(64) for _ in range(25)]
    prints = base + [b ^ sum(1 << rng.randrange(64) for _ in range(rng.randint(0, 5))) for b in base for _ in range(6)]
    prints += [base[0] ^ (1 << i) ^ (1 << (i * 7 + 3) % 12) for i in range(10)]  # a key that many share
    rows = [(i, f"{p % (1 << 64):016x}") for i, p in enumerate(prints)]
    members, pairs = fingerprints.within_radius(spark.createDataFrame(rows, "doc_id long, fingerprint string"), 3, few)
    first = {}
    for i, f in rows:
        first.setdefault(f, i)
    want = {(min(a, b), max(a, b)) for (x, a), (y, b) in itertools.combinations(first.items(), 2) if (int(x, 16) ^ int(y, 16)).bit_count() <= 3}
    assert {(r.a, r.b) for r in pairs.collect()} == want and want
    assert {r.doc_id: r.class_id for r in members.collect()} == {i: first[f] for i, f in rows}


def test_quality_keeps_prose_and_rejects_junk(spark):
    rng = random.Random(4)
    common = [f"word{i}" for i in range(60)]
    rows, marks = [], []
    for i in range(400):
        junk = i % 8 == 0
        w = [rng.choice(common) for _ in range(rng.randint(8, 80))]
        rows.append((i, " ".join(x.upper() + "!!" for x in w) if junk else " ".join(w).capitalize() + "."))
        if i < 200:
            marks.append((i, int(not junk), 0))
    got = quality.resample(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(marks, "doc_id long, quality int, toxic int")).collect()
    assert sorted(r.place for r in got) == list(range(400))
    wrong = [r.doc_id for r in got if r.kept == (r.doc_id % 8 == 0)]
    assert len(wrong) <= 4
    order = sorted(got, key=lambda r: (-r.key, r.doc_id))
    assert [r.doc_id for r in order] == [r.doc_id for r in sorted(got, key=lambda r: r.place)]


def slow_features(text):
    """Features of a text one by one, with the operator's hash of a single token."""
    import pyarrow as pa

    tokens = re.findall(r"\w+|[^\w\s]+", text)
    n, mix, out = quality.BUCKETS, 0x9E3779B97F4A7C15, {}
    h = [int(quality._hashes(pa.array([t]))[0]) for t in tokens]
    for i, x in enumerate(h):
        form, one = x % n, x // n
        feats = [one % n, 2 * n + form]
        if i + 1 < len(h):
            y = h[i + 1]
            if x == y:
                feats.append(n)
            else:
                left = (form * mix % 2**64) ^ (one % 64)
                right = (y % n) ^ ((y // n * mix % 2**64 >> 58) << 20)
                feats.append(n + 1 + ((left ^ right) * mix % 2**64 >> 24) % (n - 1))
        for f in feats:
            out[f] = out.get(f, 0) + 1
    return out


def test_quality_equals_brute_force(spark):
    from math import log

    rng = random.Random(11)
    rows = [(i, " ".join(rng.choice(["The", "cat", "sat!!", "ON", "mat", "x9", "--", "mat mat"]) for _ in range(rng.randint(0, 30)))) for i in range(120)] + [(120, None)]
    labels = [(i, i % 3 and 1, 0) for i in range(40)]
    counts = {i: slow_features(t or "") for i, t in rows}
    n, kinds = quality.BUCKETS, quality.KINDS

    def total(ids):
        out = [0] * (n * kinds)
        for i in ids:
            for f, c in counts[i].items():
                out[f] += c
        return out

    raw, good = total(counts), total(i for i, q, _ in labels if q)
    w = {}
    for f in {f for c in counts.values() for f in c}:
        k = slice(f // n * n, f // n * n + n)
        q = (raw[f] + quality.FLOOR) / (sum(raw[k]) + quality.FLOOR * n)
        w[f] = log((good[f] + quality.PRIOR * q) / (sum(good[k]) + quality.PRIOR) / q)
    docs, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in quality.resample(docs, marks).collect()}
    for i, c in counts.items():
        want = sum(w[f] * m for f, m in c.items())
        assert got[i].n_features == sum(c.values())
        assert got[i].importance == pytest.approx(want, abs=1e-4)
        assert got[i].rate == pytest.approx(want / (sum(c.values()) + quality.PSEUDO), abs=1e-5)
    level = quality.best_level(np.array([got[i].rate for i, q, _ in labels if q]), np.array([got[i].rate for i, q, _ in labels if not q]))
    assert sum(r.kept for r in got.values()) == sum(r.rate >= level for r in got.values())
    for k, want in ((17, 17), (0.5, 60)):
        drawn = quality.resample(docs, marks, k).collect()
        assert {r.doc_id for r in drawn if r.kept} == {r.doc_id for r in sorted(drawn, key=lambda r: (-r.key, r.doc_id))[:want]}


def test_level_parts_good_from_bad():
    assert quality.best_level(np.array([1.0, 2.0, 3.0]), np.array([-2.0, -1.0, 1.5])) == 0.0
    assert quality.best_level(np.array([1.0]), np.array([])) == 0.0


@pytest.mark.parametrize("size", [40, 400])
def test_short_junk_goes_whatever_the_labelled_sample(spark, size):
    rng = random.Random(size)
    words_ = [f"word{i}" for i in range(60)]
    rows = [(i, " ".join(rng.choice(words_) for _ in range(rng.randint(5, 60)))) if i % 4 else (i, "BUY NOW!!! " * rng.randint(1, 3)) for i in range(600)]
    marks = [(i, int(i % 4 > 0), 0) for i in range(size)]
    got = quality.resample(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(marks, "doc_id long, quality int, toxic int")).collect()
    assert sum(r.kept == (r.doc_id % 4 == 0) for r in got) <= 12


def test_pair_sum_equals_brute_force():
    rng = np.random.default_rng(2)
    learned = np.sort(rng.choice(5000, 60, replace=False))
    m = toxicity.Machine(-0.3, learned, rng.normal(size=60), rng.normal(size=(60, toxicity.FACTORS)))
    found = [np.sort(rng.choice(5000, n, replace=False)) for n in (0, 1, 7, 400, 3000)]
    for f, got in zip(found, m.margin(found)):
        at = [k for k, t in enumerate(learned) if t in set(f.tolist())]
        want = m.bias + sum(m.w[k] for k in at) + sum(float(m.v[a] @ m.v[b]) for a, b in itertools.combinations(at, 2))
        assert got == pytest.approx(want, abs=1e-9)


def test_pairs_of_neutral_terms_are_learned():
    """A label that only two terms together tell, each with a neutral share."""
    rng = random.Random(6)
    found, toxic = [], []
    for _ in range(3000):
        a, b = rng.random() < 0.5, rng.random() < 0.5
        found.append(toxicity.terms(" ".join([f"n{rng.randrange(300)}" for _ in range(10)] + ["insultword"] * a + ["groupword"] * b)))
        toxic.append(float(a != b))
    m = toxicity.fit(found[:2000], np.array(toxic[:2000]))
    right = (m.score(found[2000:]) >= 0.5) == np.array(toxic[2000:], bool)
    assert right.mean() > 0.95


def test_held_out_labels_are_never_learned(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    out = toxicity.remainder() == toxicity.HELD_OUT
    turned = labels.withColumn("toxic", toxicity.F.when(out, 1 - toxicity.F.col("toxic")).otherwise(toxicity.F.col("toxic")))
    one, two = (toxicity.train(docs, lab) for lab in (labels, turned))
    assert labels.where(out).count() > 0 and one.bias == two.bias and (one.w == two.w).all() and (one.v == two.v).all()
    moved = docs.withColumn("lang", toxicity.F.lit("zz")).withColumn("source", toxicity.F.lit("zz"))
    assert toxicity.toxicity(docs, labels).collect() == toxicity.toxicity(moved, labels).collect()


def test_machine_learns_a_pair_that_linear_weights_miss():
    rng = random.Random(6)
    found, toxic = [], []
    for _ in range(3000):
        insult, group = rng.random() < 0.4, rng.random() < 0.4
        text = " ".join([f"n{rng.randrange(300)}" for _ in range(10)] + ["insultword"] * insult + ["groupword"] * group)
        found.append(toxicity.terms(text))
        toxic.append(float(insult and group))
    m = toxicity.fit(found, np.array(toxic))
    score = lambda t: float(m.score([toxicity.terms(t)])[0])
    assert score("n1 insultword groupword") > 0.8 > 0.3 > max(score("n1 insultword"), score("n1 groupword"), score("n1 n2"))
    a, b = (toxicity.terms(t) for t in ("insultword", "groupword"))
    assert sum(float(m.v[m.place[i]] @ m.v[m.place[j]]) for i in a for j in b) > 0.5


def test_held_out_rows_are_told_and_never_learned(spark, odd, labels):
    for r in toxicity.toxicity(odd, labels).collect():
        assert r.held_out == (zlib.crc32(str(r.doc_id if r.doc_id is not None else "").encode()) % 4 == 2)
        assert 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.3)


ODD_TEXTS = ["hello  world", " lead", "\tx\n\ny", "ﬁ ½ é", "", "   ", "<s> </s> <unk> <0x41> ▁a", "a\u0000b", "퟿😀", "​　x", "\n", "a \n b", "▁▁", "abc" * 500, "\r\n\r\n", "a b", "it's 12 o'clock<|endoftext|>", "x\x1c y"]


def mixed_texts(n):
    rng = random.Random(7)
    return ODD_TEXTS + ["".join(rng.choice([" ", "\n", "a", "the", "'s", "12", ".", "!!", "\t", "é", "日", "ing", "▁", "😀", "́"]) for _ in range(rng.randint(0, 40))) for _ in range(n)]


def test_pieces_equal_the_library():
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=queries.PIECE_BPE)
    own = pieces.PieceCodec(queries.PIECE_BPE)
    for t in mixed_texts(1500):
        ids = library.encode(t)
        assert own.encode(t) == ids and own.decode(ids) == library.decode(ids)
        assert own.digest(t) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(library.decode(ids).encode()).hexdigest())


def test_pieces_keep_little_at_once():
    """Before, up to 16 million characters were encoded together (a peak of 687 MB here),
    and a kept cut was an entry of two tables, of several objects (371 bytes here)."""
    import tracemalloc

    own = pieces.PieceCodec(queries.PIECE_BPE)
    texts = [" ".join(f"wort{(k + i) % 997}" for i in range(8_000)) for k in range(200)]
    own.digests(texts[:1])
    tracemalloc.start()
    try:
        got = own.digests(texts)
        assert tracemalloc.get_traced_memory()[1] < 200e6
        tracemalloc.reset_peak()
        held = tracemalloc.get_traced_memory()[0]
        own.digests([f"merk{k}x{k % 7}" for k in range(20_000)])
        own.fits.clear()
        assert tracemalloc.get_traced_memory()[0] - held < 250 * 20_000
    finally:
        tracemalloc.stop()
    assert got == [own.digest(t) for t in texts]


def test_pieces_keep_marks_that_stand_in_a_piece():
    import sentencepiece

    library = sentencepiece.SentencePieceProcessor(model_file=queries.PIECE_BPE)
    own = pieces.PieceCodec(queries.PIECE_BPE)
    odd = ["a ,b", " .", "x", "a, (b). \"c\"", "a\n,\n", "▁", "▁ ▁.", "  ,,  ", "e.g. 3,5%", "日本。, 語!", "\0 a", "n\n\nn ", "\n", " "]
    for t in odd + [" ".join(odd)]:
        assert own.encode(t) == library.encode(t)
        assert own.digests([t]) == [own.digest(t)]


def test_piece_columns_round_trip(spark, odd):
    enc = pieces.encode_pieces(odd, queries.PIECE_BPE)
    got = pieces.decode_pieces(enc, queries.PIECE_BPE).select("text", "decoded").collect()
    assert all((r.text or "").replace("▁", " ") == r.decoded for r in got)


def test_token_files_hold_the_library_ids(spark, tmp_path):
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(queries.BYTE_BPE)
    rows = [(i * 3, t) for i, t in enumerate(mixed_texts(200))]
    random.Random(1).shuffle(rows)
    folder = str(tmp_path / "tokens")
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    manifest = tokenfile.write_token_files(df, queries.BYTE_BPE, 0, folder, rows_per_chunk=30)
    got = sorted(tokenfile.read_token_files(manifest, folder, "<u2", 3).collect())
    at = 0
    for r, (i, t) in zip(got, sorted(rows)):
        ids = [*library.encode(t, add_special_tokens=False).ids, 0]
        assert (r.doc_id, r.start, r.n_tokens) == (i, at, len(ids))
        assert np.frombuffer(r.ids, "<u4").tolist() == ids
        at += len(ids)


def test_licence_rules_need_their_order(spark):
    m2, m3 = licences.SENTENCES["m2"].capitalize(), licences.SENTENCES["m3"].capitalize()
    texts = [f"Intro here. {m2}:\nmore text\n{m3}.", f"{m3}. {m2}.", "Released under  the MIT\tLicense. All rights reserved!", "nothing", None]
    got = {r.doc_id: r for r in licences.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i].licences for i in range(5)] == ["mit text", "", "mit notice, rights reserved", "", ""]
    assert got[2].kinds == "permissive, proprietary" and got[0].n_known == 2


def test_shards_fit_and_split_only_where_needed(spark, tmp_path):
    rng = random.Random(8)
    rows = [(i, "x" * rng.randint(0, 900)) for i in range(600)] + [(1000, "y" * 5000), (7777, "z" * 600), (7777, "z" * 600)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sharding.assign_shards(df, 1000).collect()
    assert len(got) == len(rows)
    total = {}
    for r in got:
        total[r.shard] = total.get(r.shard, 0) + r.n_bytes
    assert all(total[r.shard] == r.shard_bytes for r in got)
    assert all(r.fits == (r.shard_bytes <= 1000) for r in got)
    assert {r.doc_id for r in got if not r.fits} == {1000, 7777}
    hashes = {r.doc_id: int(hashlib.md5(str(r.doc_id).encode()).hexdigest()[:15], 16) for r in got}
    size = {(r.doc_id, r.n_bytes): r for r in got}
    for r in size.values():  # the prefix one bit shorter does not fit
        if r.shard.startswith("bucket") and r.depth:
            above = sum(x.n_bytes for x in got if x.n_bytes <= 1000 and hashes[x.doc_id] >> (60 - r.depth + 1) == r.prefix >> 1)
            assert above > 1000
    mixed = spark.createDataFrame([*rows, (7777, "z" * 3000), (7777, "z" * 2000), (None, "n" * 1500), (None, "n")], "doc_id long, text string")
    sharding.write_shards(mixed, str(tmp_path / "out"), 1000)
    written = sorted(((r.doc_id, r.text) for r in spark.read.parquet(str(tmp_path / "out")).collect()), key=str)
    assert written == sorted(((r.doc_id, r.text) for r in mixed.collect()), key=str)
    both = [r for r in sharding.assign_shards(mixed, 1000).collect() if r.doc_id == 7777 and r.n_bytes > 1000]
    assert [r.shard_bytes for r in both] == [5000, 5000] and len({r.shard for r in both}) == 1


def lpc_stream(samples, bps=16):
    """A small two-channel stream with an LPC subframe, an escaped partition and
    a side channel, written bit by bit."""
    bits = []

    def put(value, n):
        bits.extend((value >> (n - 1 - i)) & 1 for i in range(n))

    left, right = samples
    n = len(left)
    side = [a - b for a, b in zip(left, right)]
    put(0, 1), put(32 + 1, 6), put(0, 1)  # LPC of order 2
    for s in left[:2]:
        put(s & (1 << bps) - 1, bps)
    put(4 - 1, 4), put(1, 5), put(3, 4), put(-1 & 15, 4)  # precision 4, shift 1, weights 3/2 and -1/2
    put(1, 2), put(1, 4)  # 5-bit Rice parameters, two partitions
    res = [left[i] - ((3 * left[i - 1] - left[i - 2]) >> 1) for i in range(2, n)]
    half = n // 2
    put(31, 5), put(20, 5)
    for r in res[: half - 2]:
        put(r & (1 << 20) - 1, 20)
    put(3, 5)
    for r in res[half - 2 :]:
        u = 2 * r if r >= 0 else -2 * r - 1
        put(0, u >> 3), put(1, 1), put(u & 7, 3)
    put(0, 1), put(1, 6), put(0, 1)
    for s in side:
        put(s & (1 << bps + 1) - 1, bps + 1)
    while len(bits) % 8:
        bits.append(0)
    body = bytes(int("".join(map(str, bits[i : i + 8])), 2) for i in range(0, len(bits), 8))
    head = bytes([0xFF, 0xF8, 6 << 4, 8 << 4 | 4 << 1, 0, n - 1])
    frame = head + bytes([flac.crc8(head)]) + body
    frame += int(flac.crc16_each([frame])[0]).to_bytes(2, "big")
    pcm = np.array([left, right], "<i2").T.tobytes()
    info = bytes([0, n, 0, n]) + bytes(6) + ((8000 << 44) | (1 << 41) | (bps - 1 << 36) | n).to_bytes(8, "big") + hashlib.md5(pcm).digest()
    return b"fLaC\x80" + len(info).to_bytes(3, "big") + info + frame


def test_flac_reads_other_kinds_of_frames():
    rng = np.random.default_rng(1)
    left = np.cumsum(rng.integers(-40, 40, 192)).tolist()
    right = np.cumsum(rng.integers(-40, 40, 192)).tolist()
    (x, at), = flac.decode_streams([lpc_stream((left, right))])
    assert x[:, 0].tolist() == left and x[:, 1].tolist() == right and at.tolist() == [0]


def test_flac_round_trip_and_checksums(spark):
    rng = random.Random(9)
    payloads = [flac.padded(t) for t in mixed_texts(60)] + [bytes(rng.randrange(256) for _ in range(flac.BLOCK * 2 + 192)), bytes([0, 255] * 960), b"\0" * 1152]
    streams = flac.encode_streams(payloads)
    for (x, at), p, s in zip(flac.decode_streams(streams), payloads, streams):
        assert (x[:, 0].astype(np.uint8) ^ np.uint8(128)).tobytes() == p
        assert at.tolist() == list(range(0, len(p), flac.BLOCK))
        info, first, _ = flac._read_head(s)
        slow = []
        while first < len(s):
            part, first = flac._slow_frame(s, first, info)
            slow.append(part[0])
        assert (np.concatenate(slow) == x[:, 0]).all()
    for at in (-1, -20, 12, len(streams[5]) - 100):
        bad = bytearray(streams[5] if at != len(streams[5]) - 100 else streams[-3])
        bad[at] ^= 4
        with pytest.raises(flac.FlacError):
            flac.decode_streams([bytes(bad)])
    assert flac._coded_number(0x7F) == b"\x7f" and flac._coded_number(0x80) == b"\xc2\x80" and flac._coded_number(0x10000) == "\U00010000".encode()


def test_damaged_streams_raise_only_flac_errors():
    streams = flac.encode_streams([flac.padded("some text " * 300), flac.padded("x"), bytes(range(256)) * 6])
    streams.append(lpc_stream((list(range(192)), [5] * 192)))
    rng = random.Random(2)
    for s in streams:
        for at in [*range(0, min(len(s), 90)), *(rng.randrange(len(s)) for _ in range(60))]:
            for bad in (s[:at], s[:at] + bytes([s[at] ^ (1 << rng.randrange(8))]) + s[at + 1 :]):
                try:
                    flac.decode_streams([bad])
                except flac.FlacError:
                    pass


def test_spans_equal_slices_and_read_their_frames_alone(spark):
    rng = np.random.default_rng(1)
    payload = bytes(rng.integers(0, 60, flac.BLOCK * 5 + 384, dtype=np.uint8))
    (s,) = flac.encode_streams([payload])
    whole = flac.decode_streams([s])[0][0]
    for lo, hi in ((0, 10), (1000, 1300), (flac.BLOCK * 5, 10**6), (2304, 2304), (10**6, 10**6 + 5)):
        assert (flac.decode_streams([s], [(lo, hi)])[0][0] == whole[lo:hi]).all()
    info, first, points = flac._read_head(s)
    at = first + points[4][1] + 40
    bad = s[:at] + bytes([s[at] ^ 8]) + s[at + 1 :]
    assert (flac.decode_streams([bad], [(0, flac.BLOCK)])[0][0] == whole[: flac.BLOCK]).all()
    with pytest.raises(flac.FlacError):
        flac.decode_streams([bad], [(points[4][0], points[4][0] + 1)])
    left, right = list(range(192)), [5] * 192
    assert flac.decode_streams([lpc_stream((left, right))], [(3, 9)])[0][0][:, 0].tolist() == left[3:9]
    df = spark.createDataFrame([(1, "abc " * 2000), (2, None)], "doc_id long, text string")
    got = {r.doc_id: (np.frombuffer(r.pcm, np.uint8) ^ np.uint8(128)).tobytes() for r in flac.pcm_span(flac.encode_column(df), 2000, 7).collect()}
    assert got == {1: flac.padded("abc " * 2000)[2000:2007], 2: b""}


def test_pcm_blocks_seek(spark):
    df = spark.createDataFrame([(1, "abc " * 2000), (2, None)], "doc_id long, text string")
    got = flac.pcm_blocks(flac.encode_column(df)).orderBy("doc_id", "block").collect()
    text = b"".join((np.frombuffer(r.pcm, np.uint8) ^ np.uint8(128)).tobytes() for r in got if r.doc_id == 1)
    assert text == flac.padded("abc " * 2000)
    assert [r.sample_offset for r in got if r.doc_id == 1] == list(range(0, len(text), flac.BLOCK))
