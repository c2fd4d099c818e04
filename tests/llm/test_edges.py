"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing extra columns, for every operator and stage."""

import base64
import hashlib

import pytest

import corpus_pipeline
from selsketch.llm import decontaminate, licenses, near_dup, packing, quality, secrets, substring, token_counts, toxicity, warc

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, w long, key string, h long, c long, spans string, _salt long"
WORDS = " ".join(f"word{i}" for i in range(60))
LONG = " ".join(f"x{i % 977} y{i}" for i in range(40_000))


def rows():
    texts = [None, "", "  \n\t ", "one", WORDS, WORDS, "tail " + WORDS + " more", LONG, "token = abcdef123456 and " + WORDS, "ÄÖÜ ß naïve — 日本語 " * 30]
    out = [(i, t, "en", f"s{i % 3}", len(t or ""), 1, "k", 2, 3, "x", 4) for i, t in enumerate(texts)]
    return [*out, out[4], (None, WORDS, None, None, None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def bench(spark):
    return spark.createDataFrame([(1, " ".join(f"word{i}" for i in range(10, 40)), "x"), (2, None, "x"), (3, "", "x"), (4, "too short", "x")], "item_id long, text string, doc_id string")


OPS = {
    "near_dup": near_dup.near_duplicates, "substring": substring.without_repeats, "packing": packing.pack, "tokens": token_counts.token_counts,
    "secrets": secrets.secrets, "licenses": licenses.licenses, "quality": quality.quality,
    "toxicity": lambda d: toxicity.score(d, toxicity.train(d.sparkSession.createDataFrame([(i, ("hello there", "you idiot")[i % 2], i % 2) for i in range(16)], "doc_id long, text string, toxic int"))),
}


@pytest.mark.parametrize("name", sorted(OPS))
def test_rows_survive(docs, none, name):
    got = OPS[name](docs).collect()
    if name != "packing":
        assert sorted(str(r["doc_id"]) for r in got) == sorted(str(r[0]) for r in rows())
    assert OPS[name](none).collect() == []


def test_near_duplicates(docs):
    got = {}
    for r in near_dup.near_duplicates(docs).collect():
        got.setdefault(r["doc_id"], []).append((r["n_shingles"], r["component_id"], r["kept"]))
    assert got[0] == got[0] and got[0][0] == (0, 0, True) and got[1][0] == (0, 1, True) and got[3][0] == (1, 3, True)
    assert got[4] == [(56, 4, True)] * 2 and got[5] == [(56, 4, False)] and got[6] == [(58, 4, False)]
    assert got[None] == [(56, None, True)]


def test_several_texts_of_one_id_keep_all_their_links(spark):
    a, b, c, d = (" ".join(f"{x}{i}" for i in range(40)) for x in "abcd")
    rows_ = [(1, a), (1, b), (2, a + " z"), (3, b + " z"), (9, c), (9, d), (7, c + " y"), (5, d + " y"), (9, ""), (12, a)]
    for order in (rows_, rows_[::-1]):
        got = near_dup.near_duplicates(spark.createDataFrame(order, "doc_id long, text string")).collect()
        assert sorted((r["doc_id"], r["n_shingles"] > 0, r["component_id"]) for r in got) == sorted([(1, True, 1), (1, True, 1), (2, True, 1), (3, True, 1), (9, True, 5), (9, True, 5), (7, True, 5), (5, True, 5), (9, False, 9), (12, True, 1)])


def test_small_sets_at_the_threshold_are_linked(spark):
    rng = __import__("numpy").random.default_rng(3)
    rows_, i = [], 0
    for _ in range(1500):  # pairs that share exactly 3 of 4 shingles
        w = [f"w{x}" for x in rng.integers(0, 10**9, 8)]
        rows_ += [(i, " ".join(w)), (i + 1, " ".join(w[:7]))]
        i += 2
    got = {r["doc_id"]: r["component_id"] for r in near_dup.near_duplicates(spark.createDataFrame(rows_, "doc_id long, text string")).collect()}
    assert all(got[j + 1] == j for j in range(0, i, 2))


def test_substring(docs):
    got = {r["doc_id"]: r for r in substring.without_repeats(docs).collect()}
    assert (got[0]["n_words"], got[0]["n_removed"]) == (0, 0) and got[4]["n_removed"] == 0 and got[5]["n_removed"] == 60
    assert got[6]["kept_text"] == "tail more" and got[None]["n_removed"] == 0 and got[7]["n_removed"] == 0
    assert got[5]["kept_sha256"] == hashlib.sha256(b"").hexdigest()


def test_packing(docs):
    got = packing.pack(docs).collect()
    assert all(r["length"] == 1 and r["doc_tokens"] == 1 for r in got if r["doc_id"] in (0, 1))
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for own in by.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 1024


def test_secrets(docs):
    got = {r["doc_id"]: r["found"] for r in secrets.secrets(docs).collect()}
    assert not got[0] and [(s["kind"], s["start"], s["end"]) for s in got[8]] == [("assign", 0, 20)]
    clean = {r["doc_id"]: r for r in secrets.redacted(docs).collect()}
    assert clean[8]["text"].startswith("[SECRET] and") and clean[8]["n_chars"] == len(clean[8]["text"]) and clean[0]["text"] is None
    assert secrets.redacted(docs).columns == docs.columns and secrets.redacted(docs).count() == len(rows())


def test_copied_examples_are_told_from_live_ones(spark):
    df = spark.createDataFrame([(i, "password=hunter2hunter2", f"s{i}") for i in range(5)] + [(9, "password=onlymine99", "s1")], "doc_id long, text string, source string")
    got = {r["doc_id"]: r["found"] for r in secrets.secrets(df).collect()}
    assert not got[0][0]["live"] and got[0][0]["n_owners"] == 5 and got[9][0]["live"]


def test_private_keys_are_told_apart_by_their_bodies_and_cut_whole(spark):
    head, foot = "-----BEGIN RSA PRIVATE KEY-----", "-----END RSA PRIVATE KEY-----"
    body = [[hashlib.sha512(f"{i}/{j}".encode()).hexdigest().upper()[:64] for j in range(4)] + [f"tail{i}A=="] for i in range(6)]
    texts = {i: f"before {head}\n" + "\n".join(body[i]) + f"\n{foot} after" for i in range(4)}
    texts[4] = f"x {head}\nProc-Type: 4,ENCRYPTED\nDEK-Info: AES-128-CBC,0A1B\n\n" + "\n".join(body[4]) + f"\n{foot} y"
    texts[5] = f"cut {head}\n" + "\n".join(body[5]) + "\n\nprose goes on - for long"
    texts[6] = 'k = "' + head + "\\n" + "\\n".join(body[0][:2]) + "\\n" + foot + '";'
    texts[7] = f"the header {head} alone and words after"
    texts[8] = f"{head}\n" + "QUJD" * 200_000 + f"\n{foot}"
    copies = {10 + i: f"{head}\r\n" + "\r\n".join(body[1][::-1]) + f"\r\n{foot}" for i in range(4)}
    df = spark.createDataFrame([(i, t, f"s{i}") for i, t in (texts | copies).items()], "doc_id long, text string, source string")
    found = {r["doc_id"]: [s for s in r["found"] if s["kind"] == "private"] for r in secrets.secrets(df).collect()}
    assert all(len(found[i]) == 1 and found[i][0]["live"] == (i < 7 or i == 8) for i in found) and found[10][0]["n_owners"] == 4
    clean = {r["doc_id"]: r["text"] for r in secrets.redacted(df).collect()}
    assert [clean[i] for i in range(4)] == ["before [SECRET] after"] * 4 and clean[4] == "x [SECRET] y" and clean[8] == "[SECRET]"
    assert clean[5] == "cut [SECRET]\n\nprose goes on - for long" and clean[6].endswith('[SECRET]";') and clean[7] == texts[7]
    assert all(b not in t for i, t in clean.items() if i < 10 for lines in body for b in lines)


def test_contaminated(docs, none, bench):
    got = sorted((r["doc_id"], r["item_id"], r["coverage"]) for r in decontaminate.contaminated(docs, bench).where("doc_id IS NOT NULL").collect())
    assert got == [(4, 1, 1.0), (4, 1, 1.0), (5, 1, 1.0), (6, 1, 1.0), (8, 1, 1.0)]
    assert not decontaminate.contaminated(none, bench).collect() and not decontaminate.contaminated(docs, bench.limit(0)).collect()


def test_reordered_passages_are_caught(spark):
    item = [f"t{i}" for i in range(40)]
    text = " ".join(["lead", *item[20:], "middle words here", *item[:20], "end"])
    docs = spark.createDataFrame([(1, text), (2, "nothing of it " * 20)], "doc_id long, text string")
    bench = spark.createDataFrame([(i, " ".join(item) if i == 7 else f"other item {i} with words of its own a b c") for i in range(50)], "item_id long, text string")
    got = decontaminate.contaminated(docs, bench).collect()
    assert [(r["doc_id"], r["item_id"], r["coverage"], r["n_tiles"]) for r in got] == [(1, 7, 1.0, 2)]


@pytest.mark.parametrize("labels", [[], [(4, 0), (5, 0), (6, 0)], [(4, 1), (5, 1), (6, 1)], [(4, 1), (4, 0), (6, 0), (None, 1), (5, None)]])
def test_toxicity_with_few_or_contradicting_labels(spark, tmp_path, docs, labels):
    docs.select("doc_id", "text", "lang", "source", "n_chars").write.parquet(str(tmp_path / "documents.parquet"))
    spark.createDataFrame(labels, "doc_id long, toxic int").withColumn("text", __import__("pyspark").sql.functions.lit("x")).write.parquet(str(tmp_path / "labels.parquet"))
    got = toxicity.op6_toxicity(spark, str(tmp_path)).collect()
    assert len(got) == len(rows()) and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in got)
    sample = {r["doc_id"]: r["toxic"] for r in toxicity.training_rows(docs, spark.read.parquet(str(tmp_path / "labels.parquet"))).collect()}
    assert sample == {i: max(y for j, y in labels if j == i and y is not None) for i, y in labels if i is not None and y is not None and __import__("zlib").crc32(str(i).encode()) % 5}


def test_long_compressed_files_are_read_in_ranges(spark, tmp_path, monkeypatch):
    warc.register(spark)
    rows_ = [(f"urn:x:{i}", "response", f"http://h/{i}", hashlib.sha512(str(i).encode()).digest() * 40, None, None, None) for i in range(300)]
    rows_ = spark.createDataFrame(rows_, "record_id string, record_type string, target_uri string, payload binary, refers_to string, payload_digest string, payload_bytes long").coalesce(1)
    at = f"file://{tmp_path}/w"
    rows_.write.format("warc").mode("append").save(at)
    monkeypatch.setattr(warc, "_PARTITION_BYTES", 5000)
    schema = spark.read.format("warc").load(at).schema
    reader = warc.WarcReader({"path": at}, schema)
    parts = reader.partitions()
    got = [x for p in parts for b in reader.read(p) for x in b.column("record_id").to_pylist()]
    assert len(parts) > 3 and sorted(x for x in got if x.startswith("urn:x:")) == sorted(f"urn:x:{i}" for i in range(300))


def test_warc_round_trip(spark, tmp_path):
    pages = [(1, "u", "aa"), (2, "u\nv", "aa"), (3, None, None), (4, "u", ""), (None, "u", "zz"), (7, "é", "zz"), (7, "é", "zz"), (8, "u", "ü" * 50_000)]
    spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, digest int").write.parquet(str(tmp_path / "pages.parquet"))
    got = sorted(((r["page_id"] or 0, r["payload_bytes"], r["record_type"], r["refers_to"]) for r in warc.op1_warc(spark, str(tmp_path)).collect()), key=repr)
    want = [(0, 2, "revisit", 7), (1, 2, "revisit", 2), (2, 2, "response", None), (3, 0, "revisit", 4), (4, 0, "response", None), (7, 2, "response", None), (7, 2, "response", None), (8, 100_000, "response", None)]
    assert got == sorted(want, key=repr)
    digests = {r["page_id"]: r["payload_digest"] for r in warc.op1_warc(spark, str(tmp_path)).collect()}
    assert digests[8] == base64.b32encode(hashlib.sha1(("ü" * 50_000).encode()).digest()).decode()


@pytest.mark.parametrize("level", [0, 1])
def test_warc_predicates_and_headers_only(spark, tmp_path, level):
    warc.register(spark)
    rows_ = spark.createDataFrame([(f"urn:x:{i}", "response", f"http://h/{i}", bytes([65 + i]) * 9000, None, None, None) for i in range(20)], "record_id string, record_type string, target_uri string, payload binary, refers_to string, payload_digest string, payload_bytes long")
    at = f"file://{tmp_path}/w"
    rows_.write.format("warc").option("level", str(level)).mode("append").save(at)
    back = spark.read.format("warc").load(at)
    assert {(r["record_id"], bytes(r["payload"])) for r in back.where("record_type = 'response'").collect()} == {(r["record_id"], bytes(r["payload"])) for r in rows_.collect()}
    one = back.where("target_uri = 'http://h/7'").collect()
    assert [r["record_id"] for r in one] == ["urn:x:7"] and back.where("record_type = 'warcinfo'").count() >= 1
    assert spark.read.format("warc").option("payload", "none").load(at).where("record_type = 'response' AND payload IS NULL").count() == 20


def test_stages(spark, docs, none, bench, tmp_path):
    bench.select("item_id", "text").write.parquet(str(tmp_path / "benchmark.parquet"))
    for table in (docs, none):
        now = table
        for _, stage in corpus_pipeline.STAGES[:-1]:
            now = spark.createDataFrame(stage(spark, now, str(tmp_path)).collect(), table.schema)
            assert now.columns == table.columns
        assert corpus_pipeline.STAGES[-1][1](spark, now, str(tmp_path)).count() >= now.count()
