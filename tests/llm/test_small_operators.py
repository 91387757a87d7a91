"""Token counts, media, mixing, language and quality: references, round trips, held-out accuracy, odd input."""

import hashlib
import io
import random
import wave
import zlib

import numpy as np
import public_tokenizers
import pytest
from attrition.llm import language, media, mixing, quality, token_counts
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

PATH = public_tokenizers.path("byte_bpe_50k.json")
LIBRARY = Tokenizer.from_file(PATH)
ODD = [(1, None, None), (2, "", "s"), (None, "hello world", "s"), (3, "x" * 30_000, None), (4, " \n\t ", "s"), (4, " \n\t ", "s"), (5, "日本 <|endoftext|> é", "t")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, "clash", 0) for r in ODD], "doc_id long, text string, source string, n_tokens string, size int")


@settings(max_examples=500, deadline=None)
@given(st.lists(st.sampled_from([" ", "  ", "\n", "\t", "a", "the", "ion", "'s", "'ll", "1", "22", "é", "ß", "日本", "<|endoftext|>", "<|end", "!!", ".", "　", "\x1c", "\x85", "👍🏽", "²", "_"]), max_size=30).map("".join))
def test_token_counts_equal_the_library(text):
    assert token_counts.ranks_at(PATH).count(text) == len(LIBRARY.encode(text, add_special_tokens=False).ids)


def test_token_counts_of_tables(spark, sf, odd):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").union(odd.select("doc_id", "text"))
    got = sorted((str(r[0]), *r[1:]) for r in token_counts.token_counts(docs, PATH).collect())
    want = sorted((str(k), len((t or "").encode()), n := len(LIBRARY.encode(t or "", add_special_tokens=False).ids), n > 1024) for k, t in docs.collect())
    assert got == want


def test_a_very_long_piece_is_no_trap():
    assert token_counts.ranks_at(PATH).count("ab" * 100_000) == len(LIBRARY.encode("ab" * 100_000).ids)


def test_media_round_trip_and_features(odd):
    rows = media.media_columns(odd, keep_media=True, keep_pairs=True).collect()
    assert len(rows) == len(ODD)
    for r, (k, t, _) in zip(rows, ODD):
        payload = (t or "").encode()
        payload += b" " * (-len(payload) % 192 if payload else 192)
        with wave.open(io.BytesIO(r["media"])) as w:
            assert w.readframes(w.getnframes()) == payload and w.getsampwidth() == 1
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["tail_crc32"] == zlib.crc32(payload[-16:]) and r["media_bytes"] == len(r["media"])
        assert r["doc_id"] == k and r["n_frames"] == len(payload) // 96 - 1 and r["n_pairs"] == len(r["pairs"])
        assert all(code >> 24 < r["n_frames"] for code in r["pairs"])
    assert rows[4]["feature"] == rows[5]["feature"]


def plain_pairs(payload):
    """Pairs of one payload, frame by frame, bin by bin."""
    window = np.hanning(192).astype(np.float32)
    frames = [(np.frombuffer(payload[i : i + 192], dtype=np.uint8).astype(np.float32) - 128) * window for i in range(0, len(payload) - 191, 96)]
    best = []
    for f in frames:
        spectrum = np.abs(np.fft.rfft(f)).astype(np.float32)
        best.append([max(((float(spectrum[i]), -i) for i in range(low, high))) for low, high in ((1, 12), (12, 28), (28, 56), (56, 97))])
    n = len(frames)
    is_peak = lambda t, b: all(best[t][b][0] >= best[u][b][0] for u in (t - 1, t + 1) if 0 <= u < n)
    found = {(t, b): -best[t][b][1] for t in range(n) for b in range(4) if is_peak(t, b)}
    return sorted(t << 24 | x << 16 | found[t + g, c] << 8 | g for (t, b), x in found.items() for g in (1, 2, 3) for c in (b, b + 1) if (t + g, c) in found)


def test_pairs_equal_a_plain_version(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(40)
    for r, (t,) in zip(media.media_columns(docs).collect(), docs.select("text").collect()):
        assert r["pairs"] == plain_pairs(media.padded(t)[1])
    assert plain_pairs(b" " * 192) == []


def test_peaks_find_a_tone_and_blocks_change_nothing(monkeypatch):
    tone = (128 + 100 * np.sin(2 * np.pi * 20 * np.arange(192 * 50) / 192)).astype(np.uint8)
    bins, loud = media.spectra(tone)
    assert (bins[:, 1] == 20).all() and len(bins) == 99
    monkeypatch.setattr(media, "BLOCK_FRAMES", 7)
    assert (media.spectra(tone)[0] == bins).all() and (media.spectra(tone)[1] == loud).all()


def test_mixing_meets_targets_and_caps(spark, odd):
    rng = random.Random(1)
    rows = [(i, "w " * rng.randrange(1, 40), s) for i, s in enumerate(s for s, n in (("a", 300), ("b", 900), ("c", 600), ("d", 150), (None, 300), ("é", 80)) for _ in range(n))]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(docs).groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("taken"), F.max("target").alias("target"), F.max("source_size").alias("own"), F.max("copies").alias("most")).collect()
    total = sum(r["own"] for r in got)
    assert sum(r["target"] for r in got) == pytest.approx(1.5 * total)
    for r in got:
        assert r["target"] <= 2 * r["own"] + 1e-6 and r["most"] <= 2 and abs(r["taken"] - r["target"]) < 0.12 * r["own"] + 60
    free = {r["source"]: r["target"] for r in got if r["target"] < 2 * r["own"] - 1e-6}
    weight = {"a": 5, "b": 2, "c": 1, "d": 5, "é": 2, None: 1}
    assert len({round(t / weight[s], 6) for s, t in free.items()}) == 1
    copies = {r["doc_id"]: r["copies"] for r in mixing.mix(docs).collect()}
    out = mixing.emitted(docs)
    assert out.columns == docs.columns
    assert {r["doc_id"]: r["n"] for r in out.groupBy("doc_id").agg(F.count("*").alias("n")).collect()} == {k: n for k, n in copies.items() if n}
    assert mixing.mix(odd).count() == len(ODD) and mixing.mix(odd.limit(0)).count() == 0 and mixing.emitted(odd.limit(0)).count() == 0


@pytest.fixture(scope="module")
def small(spark):
    return spark.read.parquet("/root/testdata/sf0.01/documents.parquet")


def test_language_holds_out_and_is_right(spark, small, odd):
    got = language.identify(small).join(small.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r["held_out"]]
    assert {r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got} == {True}
    assert np.mean([r["lang"] == r["lang_pred"] for r in held]) > 0.97 and all(0 <= r["score"] <= 1 for r in got)
    some = odd.withColumn("lang", F.lit("en"))
    rows = {str(r["doc_id"]): r for r in language.identify(some).collect()}
    assert rows["1"]["lang_pred"] == rows["2"]["lang_pred"] == rows["4"]["lang_pred"] == "und" and rows["None"]["lang_pred"] == "en" and not rows["None"]["held_out"]
    kept = language.accepted(some, least=0.3)
    assert kept.columns == some.columns and sorted(str(r["doc_id"]) for r in kept.collect()) == ["3", "5", "None"]
    bare = odd.withColumn("lang", F.lit(None).cast("string"))
    assert {r["lang_pred"] for r in language.identify(bare).collect()} == {"und"} and language.identify(some.limit(0)).count() == 0


def test_language_windows_and_tables_equal_the_plain_network():
    rng = np.random.default_rng(2)
    net = language.train(rng.integers(0, 256, (6, 259)).astype(np.uint8), np.arange(6) % 2, ["a", "b"], filters=4, embedding=3, epochs=2)
    text = bytes(rng.integers(0, 256, 700).astype(np.uint8))
    windows, owner, held = language.windows_of([text, b"x"])
    assert owner.tolist() == [0, 0, 0, 1] and held.tolist() == [256, 256, 188, 1]
    assert windows[0, 256:].tolist() == list(text[256:259])
    plain = []
    for w in windows:
        top = []
        for f in net.filters:
            n = len(f)
            z = [sum(net.embed[w[p + j]] @ f[j] for j in range(n)) for p in range(language.WINDOW)]
            top.append(np.max(z, axis=0))
        h = np.maximum(np.concatenate(top) + net.filter_bias, 0) @ net.dense + net.dense_bias
        plain.append(h - np.log(np.exp(h).sum()))
    assert np.allclose(net.folded().log_probabilities(windows), plain, atol=1e-4)


def test_quality_on_held_out_labels(spark, small, odd):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = quality.classify(small, labels).join(labels.withColumnRenamed("quality", "q").select("doc_id", "q"), "doc_id").where("held_out").collect()
    assert np.mean([(r["quality"] >= 0.5) == (r["q"] == 1) for r in got]) > 0.93
    rows = quality.classify(odd.withColumn("lang", F.lit(None).cast("string")), labels).collect()
    assert len(rows) == len(ODD) and all(0 <= r["quality"] <= 1 for r in rows)
    none = quality.classify(small.limit(20), labels.limit(0)).collect()
    assert {round(r["p_quality"], 6) for r in none} == {0.5}
    assert quality.classify(small.limit(0), labels).count() == 0


def test_sparse_sites_stay_near_their_parents(spark):
    good, bad = "a plain and quiet text about many things. " * 4, "!!! ### $$$ &&& " * 12
    rows = [(i, (good if i % 10 else bad) + str(i), "big", "en") for i in range(200)] + [(i, bad + str(i), "worse", "en") for i in range(200, 400)] + [(400, good, "tiny", "en")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string")
    labels = docs.select("doc_id", (~F.col("text").contains("###")).cast("int").alias("quality"), F.lit(0).alias("toxic"))
    got = {r["host"]: r for r in quality.classify(docs, labels).dropDuplicates(["host"]).collect()}
    assert got["worse"]["host_quality"] < 0.1 < 0.8 < got["big"]["host_quality"]
    assert got["worse"]["host_quality"] < got["tiny"]["host_quality"] < 1 - 1e-3, "one document moves a site only part of the way"


def test_language_learns_rare_labels_from_any_place_of_a_text(spark):
    """More than 200 labels, each told only by what stands behind character 16 384 of long texts."""
    rows = [(i, chr(0x4E00 + 40 * (i % 250)) * 120, f"l{i % 250:03d}") for i in range(500)]
    rows += [(1000 + i, "0 " * 9000 + w * 600, lang) for i, (w, lang) in enumerate([("abc ", "aa"), ("xyz ", "bb")] * 30)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    windows = language.labelled_windows(docs, "doc_id", "text", "lang", 800, 200_000, 3)
    assert len({r["label"] for r in windows}) == 252
    late = [bytes(r["window"]) for r in windows if r["label"] in ("aa", "bb")]
    assert any(b"abc" in w or b"xyz" in w for w in late) and len(late) == 3 * 60
    assert sorted(map(tuple, windows)) == sorted(map(tuple, language.labelled_windows(docs.repartition(7), "doc_id", "text", "lang", 800, 200_000, 3))), "reruns agree"
    assert len(language.labelled_windows(docs, "doc_id", "text", "lang", 800, 300, 3)) <= 3 * 252
    with pytest.raises(ValueError, match="252 labels"):
        language.labelled_windows(docs, "doc_id", "text", "lang", 800, 100, 3)


def test_posteriors_equal_moments_and_shrinkage_by_hand(spark):
    """Hosts and paths over every document of the smallest table, from the evidence alone, in plain Python."""
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet") for t in ("documents", "labels"))
    rows = quality.classify(docs, labels, path=F.concat_ws("/", "source", (F.col("doc_id") % 7).cast("string"))).collect()
    assert len(rows) == docs.count() and len({r["path"] for r in rows}) > 50
    mean = np.mean([r["p_quality"] for r in rows])

    def groups(by):
        out = {}
        for r in rows:
            out.setdefault(by(r), []).append(r["p_quality"])
        return out

    def strength(found, prior):
        n, k = sum(map(len, found.values())), len(found)
        within = sum(((np.array(x) - np.mean(x)) ** 2).sum() for x in found.values()) / (n - k)
        between = sum(len(x) * (np.mean(x) - prior(g)) ** 2 for g, x in found.items())
        spread = (between - (k - 1) * within) / (n - sum(len(x) ** 2 for x in found.values()) / n)
        return np.clip(within / spread, 0.5, 1e4) if spread > 0 else 1e4

    hosts, paths = groups(lambda r: r["host"]), groups(lambda r: (r["host"], r["path"]))
    a = strength(hosts, lambda g: mean)
    host = {g: (sum(x) + a * mean) / (len(x) + a) for g, x in hosts.items()}
    b = strength(paths, lambda g: host[g[0]])
    odds = lambda p: np.log(np.clip(p, 1e-6, 1 - 1e-6) / (1 - np.clip(p, 1e-6, 1 - 1e-6)))
    for r in rows:
        x, p = paths[r["host"], r["path"]], r["p_quality"]
        assert r["host_quality"] == pytest.approx(host[r["host"]], abs=1e-9)
        assert r["path_quality"] == pytest.approx((sum(x) + b * host[r["host"]]) / (len(x) + b), abs=1e-9)
        others = (sum(x) - p + b * host[r["host"]]) / (len(x) - 1 + b)
        assert r["quality"] == pytest.approx(1 / (1 + np.exp(-(odds(p) + odds(others) - odds(mean)))), abs=1e-7)


def test_sites_of_addresses_and_one_definition_of_letters(spark):
    urls = ["https://www.Ab.example/en/12?x=1", "http://ab.example/en/9", "http://ab.example/", "no address", None]
    got = [tuple(r) for r in spark.createDataFrame([(u,) for u in urls], "url string").select(*quality.site_of("url")).collect()]
    assert got[0] == got[1] == ("ab.example", "ab.example/en") and got[2] == ("ab.example", "ab.example/") and got[3][0] is None and got[4][0] is None
    odd = "a²½Ⅷ_é9 "
    short, long = (quality.shape(odd * n, [], set())[2] for n in (1, 10_000))
    assert short == long


def test_quality_takes_clashing_names_and_repeated_ids(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(30).selectExpr("*", "'x' AS host", "1 AS path", "0 AS keep", "2 AS p_quality", "'y' AS _text", "3 AS n")
    docs = docs.union(docs.limit(3).withColumn("text", F.lit("another text of the same id")))
    out = quality.classify(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    assert out.count() == 33 and {r["host"] for r in out.select("host").collect()} <= {r["source"] for r in docs.collect()}
