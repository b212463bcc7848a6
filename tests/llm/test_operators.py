"""Each operator on a small table of hard cases, against plain versions."""

import hashlib
import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).parent))
import brute as B  # noqa: E402

from canopy.llm import bpe, langid, media, near_dups, packing, pii, quality_cnn, quality_rules, repeats, sharding  # noqa: E402
from canopy.llm.entries import tokenizer_path  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, k1 string, rank string"
BASE = "the quick brown fox jumps over the lazy dog while seven wizards brew a potion of rare herbs and old stones by night "
LONG = " ".join(f"w{i * 7919 % 10007}" for i in range(400))
TEXTS = [
    None, "", "   \n\t", "a", "12 34", BASE * 2, BASE * 2, BASE * 2 + "end", BASE.upper() * 2, LONG, LONG, LONG.replace("w7919 ", "x "), LONG + " more words",
    "mail a.b+c@d-e.org, c@d.e_f@g.h and 10.0.0.255 or 999.1.1.1, 1.2.3.4.5.6.7.8", "card 4111 1111 1111 1111 no 4111 1111 1111 1112, +1 (555) 010-99-88 é🙂 x@y.z",
    "line one\nline one\n\nline two\nline one\r\n", "<|endoftext|> x<|startoftext|>y", "ΣΑΣ é İ 한국어 ½", "z" * 3000, "ab " * 900, "head " + LONG[:900] + " tail", "other " + LONG[100:1100] + " close",
]


def table(spark, texts=TEXTS):
    return spark.createDataFrame([(i, t, "en" if i % 2 else None, "s" if i % 3 else None, None, "x", "y") for i, t in enumerate(texts)], SCHEMA)


def by_id(df, *cols):
    return {r[0]: tuple(r)[1:] for r in df.select("doc_id", *cols).collect()}


def test_quality_rules(spark):
    got = by_id(quality_rules.judge(table(spark)), "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert got == {i: B.quality(t) for i, t in enumerate(TEXTS)}


def test_pii_base_spans(spark):
    got = by_id(pii.report(table(spark)), "n_email", "n_ip", "n_card", "n_phone", "base_sha256")
    assert got == {i: (*B.pii(t)[0], B.pii(t)[1]) for i, t in enumerate(TEXTS)}


def test_pii_terms_and_sanitising(spark):
    rows = [f"{'filler' * (i % 5)} note{i} zanzibar owns joe@x.org since year{i}" for i in range(6)] + [f"plain note owns since year {i}" for i in range(60)]
    docs = table(spark, rows)
    spans = by_id(pii.report(docs), "spans")
    assert all("term:" in spans[i][0] for i in range(6)) and not any(spans[i][0] for i in range(6, 66))
    clean = by_id(pii.sanitise(docs), "text")
    assert all("zanzibar" not in clean[i][0] and "[EMAIL]" in clean[i][0] and f"year{i}" in clean[i][0] and "owns" in clean[i][0] for i in range(6))
    assert all(clean[i][0] == rows[i] for i in range(6, 66))
    assert pii.sanitise(docs).columns == docs.columns


def test_pii_terms_of_values_seen_once_or_twice(spark):
    """A name beside a value of one or two sightings is judged; against a plain version on all rows."""
    rows = [f"mister quentin writes from una{i}@x.org about stock {i}" if i == 0 else f"plain stock report about nothing {i}" for i in range(60)]
    rows += ["lady ottoline keeps 10.1.2.3 for stock", "our report, ottoline has 10.1.2.3 about nothing", "copy of rosalind bo@y.net"] + ["copy of rosalind bo@y.net"] * 3 + [None]
    spans = by_id(pii.report(table(spark, rows)), "spans")
    said = {i: [rows[i][int(a) : int(b)] for k, a, b in (x.split(":") for x in spans[i][0].split(",") if x) if k == "term"] for i in range(len(rows))}
    assert said == B.terms(rows, pii.NEAR, pii.THRESHOLD)
    assert "quentin" in said[0] and "ottoline" in said[60] and "ottoline" in said[61] and all("rosalind" in said[i] for i in range(62, 66))
    assert "stock" not in said[0] and "report" not in said[61] and not any(said[i] for i in range(1, 60))


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates(spark, width):
    got = by_id(near_dups.near_duplicates(table(spark), width), "n_shingles", "component_id", "kept")
    assert got == B.near(list(enumerate(TEXTS)), width)


def test_near_duplicates_of_one_family(spark):
    words = LONG.split()[:120]
    rows = []
    for i in range(60):  # copies that differ from the base and from each other
        w = list(words)
        for j in range(i % 12):
            w[(i * 7 + j * 11) % 120] = f"y{i}x{j}"
        rows.append(" ".join(w))
    got = by_id(near_dups.near_duplicates(table(spark, rows), 2), "n_shingles", "component_id", "kept")
    assert got == B.near(list(enumerate(rows)), 2)


@pytest.mark.parametrize("limit", [16384, 3])
def test_repeats(spark, limit):
    texts = [*TEXTS, *(f"{i} before " + LONG[200:700] + f" after {i}" for i in range(9))]
    got = by_id(repeats.report(table(spark, texts), 400, limit), "n_bytes", "n_removed", "n_spans", "kept_sha256")
    assert got == {x[0]: x[1:] for x in B.repeats(list(enumerate(texts)), 400)}


def test_strip_keeps_rows_and_columns(spark):
    docs = table(spark)
    out = repeats.strip(docs, repeats.WORDS, 50)
    assert out.columns == docs.columns and out.count() == docs.count()
    text = by_id(out, "text")
    assert text[0] == (None,) and text[3] == ("a",) and text[10] == ("",)
    assert text[20][0].startswith("head ") and len(text[20][0]) < 100


def test_media(spark):
    got = by_id(media.store_and_sniff(table(spark)), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32")
    assert got == {i: B.payload(t) for i, t in enumerate(TEXTS)}


def test_sniffing_confirms_structure():
    gif = b"GIF89a\x01\x00\x01\x00\x80\x00\x00\x00\x00\x00\xff\xff\xff,\x00\x00\x00\x00\x01\x00\x01\x00\x00\x02\x02D\x01\x00;"
    payload = b"x" * 10 + gif + b"GIF89a not one, BM neither" + media.to_wav(b"abcd")
    found = media.sniff(payload, media.automaton())
    assert (10, len(gif), "gif") in found and [k for _, _, k in found] == ["gif", "wav"]
    assert media.corrected_type("text/plain", gif, media.automaton()) == "gif"
    assert media.from_wav(media.to_wav(payload)) == payload


def test_packing(spark):
    from tokenizers import Tokenizer

    path = tokenizer_path("byte_bpe_50k.json")
    tk = Tokenizer.from_file(path)
    want = {i: tk.encode(t or "", add_special_tokens=False).ids + [0] for i, t in enumerate(TEXTS)}
    seen, places = {i: 0 for i in want}, {}
    for d, s, n, crc, total, q, o in packing.pack(table(spark), path).orderBy("doc_id", "start").collect():
        assert s == seen[d] and total == len(want[d]) and crc == B.crc_ids(want[d][s : s + n])
        seen[d] += n
        places.setdefault(q, []).append((o, n))
    assert seen == {i: len(x) for i, x in want.items()}
    for v in places.values():
        at = 0
        for o, n in sorted(v):
            assert o == at
            at += n
        assert at <= 1024


def test_plan_uses_each_length_once():
    import random

    r = random.Random(3)
    h = {r.randint(1, 1024): r.randint(1, 500) for _ in range(300)}
    used = {}
    plan = packing.plan(h)
    for lengths, n in plan:
        assert sum(lengths) <= 1024
        for a in lengths:
            used[a] = used.get(a, 0) + n
    assert used == h
    least = max(sum(a * n for a, n in h.items()) / 1024, sum(n for a, n in h.items() if a > 512))
    assert sum(n for _, n in plan) < 1.04 * least


def test_bpe(spark):
    from tokenizers import Tokenizer

    path = tokenizer_path("word_bpe_49k.json")
    tk = Tokenizer.from_file(path)
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    want = {}
    for i, t in enumerate(TEXTS):
        ids = tk.encode(t or "", add_special_tokens=False).ids
        want[i] = (len(ids), sha(" ".join(map(str, ids))), sha(tk.decode(ids, skip_special_tokens=False)))
    assert by_id(bpe.encode_documents(table(spark), path), "n_tokens", "ids_sha256", "decoded_sha256") == want


def test_sharding(spark):
    rows = sharding.shard_documents(table(spark), 4).toPandas()
    assert len(rows) == len(TEXTS) and set(rows.law) == {"bytes"}
    for _, part in rows.groupby("shard"):
        assert sorted(part.slot) == list(range(len(part)))


def test_edited_map_moves_little():
    import pandas as pd

    loads = pd.DataFrame({"vslot": range(2000), "bytes": [1000 + i % 7 for i in range(2000)]})
    old = sharding.first_map(loads, 8)
    new = sharding.edited_map(old, loads, 9)
    both = old.merge(new, on="vslot")
    moved = both[both.shard_x != both.shard_y]
    assert set(moved.shard_y) == {8} and len(moved) < 260 and new.version.max() == 2


def test_language_and_quality_models(spark):
    en, xx = "the and of that with this from which ", "ñandú está según rápido niño más año "
    rows = [(i, (en if i % 2 else xx) * (1 + i % 4), "en" if i % 2 else "xx", "s", None, "x", "y") for i in range(80)] + [(90, None, None, None, None, "x", "y"), (91, "123 !!", None, None, None, "x", "y")]
    docs = spark.createDataFrame(rows, SCHEMA)
    got = by_id(langid.classify(docs, langid.fit(docs)), "lang_pred", "accepted")
    assert all(got[i] == ("en" if i % 2 else "xx", True) for i in range(80))
    assert got[90] == got[91] == ("und", False)
    labelled = docs.selectExpr("doc_id", "text", "cast(doc_id % 2 as int) as label").where("doc_id < 80")
    p = by_id(quality_cnn.score(docs, quality_cnn.fit(labelled)), "score", "predicted")
    assert all(p[i][1] == i % 2 for i in range(80)) and 0 <= p[90][0] <= 1


def test_quality_fit_passes_over_texts_that_do_not_fit(spark, monkeypatch):
    kept = []
    monkeypatch.setattr(quality_cnn, "FIT_BYTES", 2000)
    monkeypatch.setattr(quality_cnn, "train", lambda texts, y: kept.append((texts, list(y))))
    rows = [(i, "z" * 1500 if i % 4 == 0 else f"text {i}", i % 2) for i in range(40)] + [(99, "z" * 3000, 1)]
    quality_cnn.fit(spark.createDataFrame(rows, "doc_id long, text string, label int"))
    (texts, labels), = kept
    assert sum(t.startswith("text") for t in texts) == 30 and sum(map(len, texts)) <= 2000 and set(labels) == {0, 1}


def test_empty_tables(spark):
    none = table(spark).limit(0)
    path = tokenizer_path("byte_bpe_50k.json")
    for df in (quality_rules.judge(none), pii.report(none), near_dups.near_duplicates(none), repeats.report(none), repeats.strip(none), media.store_and_sniff(none), packing.pack(none, path), sharding.shard_documents(none), bpe.encode_documents(none, tokenizer_path("word_bpe_49k.json")), langid.classify(none, langid.fit(none)), quality_cnn.score(none, quality_cnn.fit(none.selectExpr("doc_id", "text", "1 as label")))):
        assert df.count() == 0


def test_repeated_rows(spark):
    docs = table(spark).union(table(spark))
    for df in (quality_rules.judge(docs), pii.report(docs), near_dups.near_duplicates(docs), repeats.report(docs), media.store_and_sniff(docs), sharding.shard_documents(docs)):
        assert df.count() == 2 * len(TEXTS)
    assert near_dups.drop_near_duplicates(docs).groupBy("doc_id").count().where("count > 1").count() == 0
