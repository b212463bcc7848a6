"""The dealt methods themselves: what they decide, against plain versions and on cases made to trip them."""

import gzip
import io
import math
import random
import sys
import zipfile
import zlib
from collections import Counter, defaultdict
from pathlib import Path

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parent))
import brute as B  # noqa: E402

import corpus_pipeline as pipeline  # noqa: E402
from canopy.llm import bpe, langid, media, near_dups, packing, pii, quality_cnn, quality_rules, repeats, sharding  # noqa: E402
from canopy.llm import kernels as K  # noqa: E402
from canopy.llm.entries import tokenizer_path  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def table(spark, texts, source=None, lang="en"):
    return spark.createDataFrame([(i, t, lang, source[i] if source else "s", None) for i, t in enumerate(texts)], SCHEMA)


def buffer(texts):
    raw = [(t or "").encode() for t in texts]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate(([0], np.cumsum([len(x) for x in raw])))


def sentence(rng, n):
    return " ".join("".join(rng.choice("abcdefghijklmnop") for _ in range(rng.randint(2, 8))) for _ in range(n))


# ---- language ID


def test_noise_and_unlearned_languages_are_rejected(spark):
    rng = random.Random(1)
    sound = {"aa": ["ba", "na", "lo", "mi", "sa"], "bb": ["trek", "vond", "zij", "och", "huis"]}
    texts = [(f"{k}", " ".join("".join(rng.choice(v) for _ in range(rng.randint(1, 3))) for _ in range(rng.randint(40, 120)))) for k, v in sound.items() for _ in range(60)]
    docs = spark.createDataFrame([(i, t, k) for i, (k, t) in enumerate(texts)], "doc_id long, text string, lang string")
    model = langid.fit(docs)
    langs, scores, taken = langid.predict([t for _, t in texts], model)
    assert langs == [k for k, _ in texts] and sum(taken) >= 0.98 * len(texts)
    other = [" ".join("".join(rng.choice(["qyx", "gwu", "pff", "ecc", "rdi"]) for _ in range(2)) for _ in range(80)), "".join(rng.choice("abcdefghijklmnopqrstuvwxyz0123456789+/") for _ in range(500))]
    assert not any(langid.predict(other, model)[2])
    assert langid.predict([None, "", "123 ...", "\U0001f600"], model) == (["und"] * 4, [0.0] * 4, [False] * 4)
    assert langid.predict(["\U0001d4b3\U0001d4b4"], model)[0][0] in ("aa", "bb")  # letters beyond the basic plane are letters


def test_every_language_is_learned(spark):
    """More languages than any fixed number, one of them with a single text."""
    rng = random.Random(2)
    rows = []
    for k in range(90):
        sounds = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(3)) for _ in range(4)]
        rows += [(len(rows) + i, " ".join(rng.choice(sounds) for _ in range(60)), f"l{k:02}") for i in range(1 if k == 7 else 3)]
    model = langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert model.languages == sorted({r[2] for r in rows})
    assert langid.predict([r[1] for r in rows], model)[0] == [r[2] for r in rows]


# ---- host rules


def test_failing_hosts_go_with_their_documents(spark):
    """Host rates, prior and limit by plain arithmetic, with two hosts that fail and a null host."""
    rng = random.Random(3)
    hosts = [f"h{i}" for i in range(30)] + ["bad", "worse", None]
    texts, source = [], []
    for h in hosts:
        for _ in range(12):
            fails = rng.random() < {"bad": 0.85, "worse": 1.0}.get(h, 0.05)
            texts.append("few words" if fails else sentence(rng, 30))
            source.append(h)
    got = {r.doc_id: r for r in quality_rules.judge(table(spark, texts, source)).collect()}
    failed = {i: B.quality(t)[5] for i, t in enumerate(texts)}
    n, f = Counter(source), Counter(h for i, h in enumerate(source) if failed[i])
    m = sum(f.values()) / len(texts)
    v = sum(f[h] ** 2 / n[h] for h in n) / len(texts) - m * m - m * (1 - m) * len(n) / len(texts)
    w = min(1000, max(1, m * (1 - m) / v - 1)) if v > 1e-12 else 1000
    limit = min(0.5, m + 3 * math.sqrt(m * (1 - m) / (w + 1)))
    rate = {h: (f[h] + m * w) / (n[h] + w) for h in n}
    assert {h for h in n if rate[h] > limit} == {"bad", "worse"}
    for i, h in enumerate(source):
        assert got[i].host_rate == pytest.approx(rate[h]) and got[i].host_limit == pytest.approx(limit)
        assert got[i].kept == (not failed[i] and rate[h] <= limit)


def test_hosts_that_fail_alike_stay(spark):
    texts = [("few" if i % 10 == 0 else sentence(random.Random(i), 25)) for i in range(200)]
    got = quality_rules.judge(table(spark, texts, [f"h{i // 20}" for i in range(200)])).collect()
    assert all(r.kept == (not r.base_failed) for r in got)


# ---- personal data


def test_secrets_and_words_far_away(spark):
    key = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"
    pad = "x " * 5000
    texts = [f'say token = "{key}" now', "plain prose with thanonontioninerthanonontioniner words", "0" * 40, f"quentin {pad}10.1.2.3 {pad}rosalind", "a" * 20 + "1"] + [f"prose number {i}" for i in range(40)]
    rows = {r.doc_id: r for r in pii.report(table(spark, texts)).collect()}
    assert rows[0].spans == f"secret:{texts[0].index(key)}:{texts[0].index(key) + 40}"
    assert [rows[i].n_spans for i in (1, 2, 4)] == [0, 0, 0]
    said = [texts[3][int(a) : int(b)] for k, a, b in (x.split(":") for x in rows[3].spans.split(",")) if k == "term"]
    assert said == ["quentin", "rosalind"] == B.terms(texts, pii.NEAR, pii.THRESHOLD)[3]
    clean = {r.doc_id: r.text for r in pii.sanitise(table(spark, texts)).collect()}
    assert clean[0] == 'say token = "[SECRET]" now'


def test_disclosure_against_plain_counts(spark):
    """Names beside values of many, few and shared sightings, among words that stand everywhere."""
    rng = random.Random(5)
    names = ["ottoline", "quentin", "rosalind", "zebedee"]
    texts = []
    for i in range(150):
        words = sentence(rng, 25).split()
        if i % 6 == 0:
            who = rng.randrange(4)
            words[10:10] = [names[who], "writes", f"{names[who]}{who}@mail.org", "from", "here"]
        if i % 9 == 0:
            words += [names[rng.randrange(4)], "here"]
        texts.append(" ".join(words))
    got = {r.doc_id: r.spans for r in pii.report(table(spark, texts)).collect()}
    want = B.terms(texts, pii.NEAR, pii.THRESHOLD)
    assert any(want.values())
    assert {i: [texts[i][int(a) : int(b)] for k, a, b in (x.split(":") for x in s.split(",") if x) if k == "term"] for i, s in got.items()} == want


# ---- packing, byte pairs


def test_long_and_repeated_texts_pack_and_encode(spark):
    from tokenizers import Tokenizer

    long = sentence(random.Random(6), 180_000)
    assert len(long) > 1_000_000
    docs = spark.createDataFrame([(1, long, None, None, None), (2, "twice", None, None, None), (2, "twice", None, None, None), (3, None, None, None, None)], SCHEMA)
    tk = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json"))
    want = Counter({1: len(tk.encode(long, add_special_tokens=False).ids) + 1, 2: 2 * (len(tk.encode("twice", add_special_tokens=False).ids) + 1), 3: 1})
    got = Counter()
    for r in packing.pack(docs, tokenizer_path("byte_bpe_50k.json")).collect():
        got[r.doc_id] += r.length
    assert got == want
    word = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    rows = sorted((r.doc_id, r.n_tokens) for r in bpe.encode_documents(docs, tokenizer_path("word_bpe_49k.json")).collect())
    assert rows == [(1, len(word.encode(long, add_special_tokens=False).ids)), (2, 1), (2, 1), (3, 0)]


# ---- quality network


def plain_score(model, text):
    """Every filter at every byte of every chunk, by loops."""
    b = text.encode()
    tops = []
    for k in range(0 if not b else 1 + max(0, -((quality_cnn.CHUNK - len(b)) // quality_cnn.STRIDE))):
        a, e = k * quality_cnn.STRIDE, min(k * quality_cnn.STRIDE + quality_cnn.CHUNK, len(b))
        tops.append([max(0.0, max(sum(float(model.filters[j, b[i + j], f]) for j in range(quality_cnn.WIDTH) if i + j < len(b)) for i in range(a, e))) for f in range(quality_cnn.FILTERS)])
    mean = [sum(t[f] for t in tops) / len(tops) if tops else 0.0 for f in range(quality_cnn.FILTERS)]
    most = [max(t[f] for t in tops) if tops else 0.0 for f in range(quality_cnn.FILTERS)]
    return 1 / (1 + math.exp(-(sum(w * x for w, x in zip(model.weights.tolist(), mean + most)) + model.bias)))


def test_scores_are_those_of_plain_loops_in_any_batch():
    rng = random.Random(7)
    good, bad = [sentence(rng, rng.randint(1, 200)) for _ in range(30)], ["".join(rng.choice("$#%&* 123") for _ in range(rng.randint(1, 900))) for _ in range(30)]
    texts = [t for pair in zip(good, bad) for t in pair]
    model = quality_cnn.train(texts, np.array([1, 0] * 30, np.float32), epochs=3)
    extra = ["", "a", "ab", "é🙂", "x" * quality_cnn.CHUNK, "y" * (quality_cnn.CHUNK + 1), sentence(rng, 400)]
    whole = quality_cnn.probability(model, *buffer(texts + extra))
    assert whole == pytest.approx([plain_score(model, t) for t in texts + extra], abs=1e-4)
    for cut in (1, 2, 7, 33):
        parts = [texts[i : i + cut] for i in range(0, len(texts), cut)]
        assert np.array_equal(np.concatenate([quality_cnn.probability(model, *buffer(p)) for p in parts]), whole[: len(texts)])
    assert quality_cnn.probability(model, *buffer(["same"] * 5 + ["z" * 3000, "same"]))[[0, 4, 6]].std() == 0
    assert ((whole[:60] >= 0.5) == np.array([True, False] * 30)).mean() > 0.95


def test_sample_keeps_its_byte_bound(spark, monkeypatch):
    monkeypatch.setattr(quality_cnn, "FIT_BYTES", 4000)
    rows = [(i, "w " * (3000 if i == 3 else 40), int(i % 2)) for i in range(60)]
    got = quality_cnn.sample(spark.createDataFrame(rows, "doc_id long, text string, label int"))
    assert 40 <= len(got) <= 50 and sum(len(t) for t, _ in got) <= 4000 and {label for _, label in got} == {0, 1}


# ---- near-duplicates


def test_pairs_within_the_distance_share_a_key():
    """The pigeonhole: any two signatures within FAR agree in all but one component of some part."""
    rng = np.random.default_rng(8)
    n = near_dups.PARTS * near_dups.SIZE
    for _ in range(500):
        a = rng.integers(0, 1 << near_dups.BITS, n)
        b = a.copy()
        where = rng.permutation(n)[: near_dups.FAR]
        b[where] += 1
        differ = (a != b).reshape(near_dups.PARTS, near_dups.SIZE).sum(1)
        assert (differ <= near_dups.ERRORS).any()


def test_bound_from_least_hashes_loses_no_link():
    rng = np.random.default_rng(9)
    for _ in range(200):
        n, keep = int(rng.integers(1, 3 * near_dups.LOW)), rng.random()
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.int64).astype(K.U) * K.U(2))
        b = np.unique(np.concatenate((a[rng.random(len(a)) < max(keep, 0.75)], rng.integers(0, 2**63, int(rng.integers(0, 40)), dtype=np.int64).astype(K.U) * K.U(2))))
        if not len(b):
            continue
        both = len(np.intersect1d(a, b))
        low = [(x[: near_dups.LOW] >> K.U(32)).astype(np.uint32).view(np.int32) for x in (a, b)]
        ok = bool(near_dups.possible(low, np.array([len(a), len(b)]), 0, np.array([1]), 80)[0])
        if 100 * both >= 80 * (len(a) + len(b) - both):
            assert ok
        elif max(len(a), len(b)) <= near_dups.LOW:
            assert not ok


def test_near_families_against_brute_force(spark):
    """Families of edited copies, of similarities around the threshold, one large; all links as brute force finds them."""
    rng = random.Random(10)
    texts = []
    for family in range(12):
        base = sentence(rng, 60).split()
        for _ in range(40 if family == 0 else 6):
            w = list(base)
            for _ in range(rng.randint(0, 7)):
                w[rng.randrange(len(w))] = sentence(rng, 1)
            texts.append(" ".join(w))
    got = {r.doc_id: (r.n_shingles, r.component_id, r.kept) for r in near_dups.near_duplicates(table(spark, texts), width=2, percent=80).collect()}
    assert got == B.near(list(enumerate(texts)), 2)


def test_rows_of_one_id_and_different_texts_stay(spark):
    rng = random.Random(11)
    a, b = sentence(rng, 40), sentence(rng, 40)
    docs = spark.createDataFrame([(1, a, None, None, None), (1, b, None, None, None), (1, a, None, None, None), (None, a, None, None, None), (5, a, None, None, None)], SCHEMA)
    got = sorted((r.doc_id or 0, r.text) for r in near_dups.drop_near_duplicates(docs).collect())
    assert got == sorted([(0, a), (1, a), (1, b)])


# ---- media


def test_carving_and_corrected_types(spark):
    z = io.BytesIO()
    inner = io.BytesIO()
    with zipfile.ZipFile(inner, "w") as f:
        f.writestr("a.txt", "inner")
    with zipfile.ZipFile(z, "w", zipfile.ZIP_STORED) as f:
        f.writestr("in.zip", inner.getvalue())
    z = z.getvalue()
    pdf = b"%PDF-1.4\n1 0 obj\nendobj\nxref\n" + b"trailer\nstartxref\n24\n%%EOF\n2 0 obj %%EOF in a string\nxref\ntrailer\nstartxref\n60\n%%EOF"
    bomb = gzip.compress(b"\0" * 50_000_000)
    wav = media.to_wav(b"sound")
    rows = [(1, b"xx" + z + b"yy", "text/plain"), (2, pdf + b" tail", "image/png"), (3, bomb, None), (4, b"plain", "text/plain"), (5, None, "text/plain"), (6, wav + pdf, "text/plain")]
    got = defaultdict(list)
    for r in media.carve(spark.createDataFrame(rows, "k long, p binary, d string"), "k", "p", "d").collect():
        got[r.id].append((r.corrected, r.start, r.kind, r.object and bytes(r.object)))
    assert ("text/plain", 2, "zip", z) in got[1] and any(x[3] == inner.getvalue() for x in got[1])
    assert got[2] == [("pdf", 0, "pdf", pdf)]
    assert got[3] == [("gzip", 0, "gzip", bomb)]
    assert got[4] == [("text/plain", None, None, None)] and got[5] == [("text/plain", None, None, None)]
    assert sorted(got[6], key=lambda x: x[1]) == [("wav", 0, "wav", wav), ("wav", len(wav), "pdf", pdf)]


def test_stored_documents_are_sniffed_and_corrected(spark):
    gif = "GIF89a"
    texts = ["plain words", None, "%PDF-1.4\nxref\ntrailer\nstartxref\n9\n%%EOF and more", gif, "plain words", "see %PDF-1.4\nstartxref\n9\n%%EOF"]
    rows = {r.doc_id: r for r in media.store_and_sniff(table(spark, texts)).collect()}
    assert [rows[i].corrected_type for i in range(6)] == ["text", "text", "pdf", "text", "text", "text"]
    assert rows[5].n_embedded == 1 and "pdf@4+" in rows[5].feature
    assert rows[5].carved_sha256 == B.sha(texts[5][4:].encode()) and rows[0].carved_sha256 == B.sha(b"")
    assert rows[0].feature == rows[4].feature != rows[1].feature
    x = np.frombuffer(("plain words" + "\0" * 53).encode(), np.uint8).astype(int) - 128
    assert f"peak={abs(x).max()},rms={np.sqrt((x * x).mean()):.3f}" in rows[0].feature


# ---- repeats


def test_digit_passes_order_like_python():
    rng = random.Random(12)
    for _ in range(60):
        depth, groups = rng.choice([8, 24, 40]), []
        rows = []
        for g in range(rng.randint(1, 6)):
            stem = bytes(rng.choice(b"ab") for _ in range(depth))
            for _ in range(rng.randint(1, 6)):
                at = rng.randint(0, depth)
                rows.append(stem[:at] + bytes(rng.choice(b"ab") for _ in range(depth - at)))
                groups.append(g)
        digits = np.frombuffer(b"".join(rows), np.uint8).reshape(len(rows), depth).view(">u8").astype(K.U)
        rank, shared = repeats.ordered(digits, np.array(groups), 8)
        order = np.argsort(rank)
        keyed = [(groups[i], rows[i]) for i in order]
        assert keyed == sorted(zip(groups, rows))
        for p in range(1, len(rows)):
            (g, x), (h, y) = keyed[p - 1], keyed[p]
            want = -1 if g != h else next((i for i in range(depth) if x[i] != y[i]), depth)
            assert shared[p] == want


def plain_word_repeats(texts, n):
    """Words inside windows of n words that begin elsewhere too."""
    words = [B.WORD.findall((t or "").encode()) for t in texts]
    seen = Counter(tuple(w[i : i + n]) for w in words for i in range(len(w) - n + 1))
    return [len({i + k for i in range(len(w) - n + 1) if seen[tuple(w[i : i + n])] > 1 for k in range(n)}) for w in words]


@pytest.mark.parametrize("limit", [5, 16_384])
def test_repeated_words_and_bytes_of_made_passages(spark, limit):
    """Short-worded passages under 400 bytes, passages in many documents, overlaps, periods and whole copies."""
    rng = random.Random(13)
    passages = [" ".join(rng.choice(["a", "bc", "def", "gh"]) + str(rng.randrange(90)) for _ in range(n)) for n in (50, 53, 60, 120, 200)]
    texts = [None, "", "ab " * 300, "short"]
    for i in range(60):
        p = passages[i % 5]
        texts.append(sentence(rng, rng.randint(0, 30)) + " " + p + (" " + passages[(i * 7) % 5] if i % 4 == 0 else "") + "\n" + sentence(rng, rng.randint(0, 30)))
    texts += [texts[6], texts[9] + " tail"]
    rows = {r.doc_id: r for r in repeats.report(table(spark, texts), 400, limit).collect()}
    assert [rows[i].n_repeated_words for i in range(len(texts))] == plain_word_repeats(texts, 50)
    assert sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in rows.values()) == sorted(B.repeats(list(enumerate(texts)), 400))


# ---- sharding


def test_map_is_stored_read_back_and_edited(spark, tmp_path):
    texts = [sentence(random.Random(i), 5 + i % 40) for i in range(600)]
    root = f"file://{tmp_path}/maps"
    docs = table(spark, texts)
    one = {r.doc_id: r for r in sharding.shard_documents(docs, 8, maps=root).collect()}
    assert sharding.stored_versions(spark, root) == [1]
    held = dict(zip(*(sharding.read_map(spark, root)[c] for c in ("vslot", "shard"))))
    for i, t in enumerate(texts):
        assert one[i].size == len(t.encode()) + 16 and one[i].text_crc32 == zlib.crc32(t.encode()) and one[i].shard == held[one[i].virtual_slot]
    size = Counter()
    for r in one.values():
        size[r.shard] += r.size
    assert max(size.values()) - min(size.values()) <= max(r.size for r in one.values())
    more = docs.union(table(spark, ["new " + t * 3 for t in texts[:80]]).withColumn("doc_id", F.col("doc_id") + 1000))
    two = {r.doc_id: r for r in sharding.shard_documents(more, 8, maps=root).collect()}
    assert sharding.stored_versions(spark, root) == [1, 2] and {r.map_version for r in two.values()} == {2}
    moved = sum(two[i].shard != one[i].shard for i in one)
    assert moved < 0.2 * len(one)
    size = Counter()
    for r in two.values():
        size[r.shard] += r.size
    assert max(size.values()) < 1.08 * sum(size.values()) / 8
    for shard in range(8):
        assert sorted(r.slot for r in two.values() if r.shard == shard) == list(range(sum(r.shard == shard for r in two.values())))


# ---- the pipeline


def test_each_stage_on_a_small_corpus(spark, tmp_path):
    """Language, near copies, passages, personal data and packing, each against a plain version of what it keeps."""
    from tokenizers import Tokenizer

    rng = random.Random(14)
    sound = {"aa": ["ba", "na", "lo", "mi", "sa"], "bb": ["trek", "vond", "zij", "och", "huis"]}
    say = lambda k, n: " ".join("".join(rng.choice(sound[k]) for _ in range(rng.randint(2, 4))) for _ in range(n))
    texts, lang = [], []
    for i in range(80):
        k = "ab"[i % 2] * 2
        texts.append(say(k, 80) + f" ask me{i}@x{i}.org now " + say(k, 30))
        lang.append(k if i % 7 else None)
    passage = say("aa", 60)
    texts[4] += " " + passage
    texts[10] = passage + " " + texts[10]
    texts += [texts[2], texts[3].replace("ask", "tell"), None, "", "12345"]
    lang += [None] * 5
    docs = spark.createDataFrame([(i, t, k, "s", None) for i, (t, k) in enumerate(zip(texts, lang))], SCHEMA)
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    sf, d, tables = str(tmp_path), spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in pipeline.STAGES:
        d = stage(spark, d, sf)
        d.write.parquet(f"{tmp_path}/{name}")
        d = tables[name] = spark.read.parquet(f"{tmp_path}/{name}")
        assert name == "packing" or d.columns == docs.columns
    by = {name: {r.doc_id: r.text for r in t.collect()} for name, t in tables.items() if name != "packing"}
    assert by["language_id"] == {i: t for i, t in enumerate(texts) if t and t != "12345"}
    near = B.near(sorted(by["language_id"].items()), 5)
    assert by["near_duplicates"] == {i: t for i, t in by["language_id"].items() if near[i][2]} and 80 not in by["near_duplicates"]
    for i, t in by["near_duplicates"].items():
        assert by["repeated_passages"][i].split() == t.replace(passage, "").split()
    assert set(by["personal_data"]) == set(by["repeated_passages"]) and all("@" not in t and "[EMAIL]" in t for t in by["personal_data"].values())
    tk, total = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json")), Counter()
    for r in tables["packing"].collect():
        total[r.doc_id] += r.length
    assert total == {i: len(tk.encode(t, add_special_tokens=False).ids) + 1 for i, t in by["personal_data"].items()}
    assert pipeline.run(spark, sf).count() == tables["packing"].count()


# ---- hard rows for all


def test_very_long_text_and_clashing_columns(spark):
    """One text of over a megabyte beside small ones, repeated rows, and columns named like the operators' own."""
    rng = random.Random(15)
    long = sentence(rng, 190_000)
    rows = [(1, long), (2, "small text of a few words"), (2, "small text of a few words"), (3, None), (4, long[:500] + " tail")]
    names = ["key", "n", "sig", "set", "h", "place", "list", "ctx", "salt", "spans", "pii", "mark", "host_rate", "vslot", "size", "draw", "label", "component", "rep", "k2", "copies"]
    docs = spark.createDataFrame([(*r, "en", "s", None, *["x"] * len(names)) for r in rows], SCHEMA + "".join(f", {c} string" for c in names))
    model = langid.fit(docs.where("false"))
    for got in (quality_rules.judge(docs), pii.report(docs), near_dups.near_duplicates(docs), repeats.report(docs), media.store_and_sniff(docs), sharding.shard_documents(docs), langid.classify(docs, model), quality_cnn.score(docs, quality_cnn.fit(docs.where("false").selectExpr("doc_id", "text", "1 as label")))):
        ids = sorted(r.doc_id for r in got.select("doc_id").collect())
        assert ids == [1, 2, 2, 3, 4]
    for stage in (near_dups.drop_near_duplicates, repeats.strip, pii.sanitise):
        assert stage(docs).columns == docs.columns
    want = B.quality(long)
    assert next(r for r in quality_rules.judge(docs).collect() if r.doc_id == 1)[1:6] == want[:5]
    assert {r.n_removed for r in repeats.report(docs).where("doc_id in (1, 4)").collect()} == {500}
