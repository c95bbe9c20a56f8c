"""Clashing columns, nulls, ties, repeated rows, empty and very long texts for every operator and stage; skew; bounded samples; broken media."""

import hashlib
import random
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tracelink.llm import fingerprints, gif, language_crf, near_dups, pieces, poisson_mix, shards, toxicity, url_rules, windows
from tracelink.llm.common import table, unused

SF = "/root/testdata/sf0.001"
#: Names that the operators use inside or add, beside the columns of documents.
CLASHES = ["k_id", "k_hash", "k_row", "k_range", "s_id", "s_key", "row", "at", "u", "node", "component_id", "kept", "streams", "cdf", "r_source", "x_source", "ident", "__k", "__text", "__guess", "guess", "rid", "x_host", "b", "tie", "own_row", "t_id", "key", "id", "n"]
random.seed(5)
WORDS = [f"w{i}" for i in range(50)]
LONG = " ".join(random.choice(WORDS) for _ in range(60_000))
BASE = " ".join(random.choice(WORDS) for _ in range(60))
ROWS = [(1, BASE, "en", "a", 1), (2, BASE, "en", "a", 1), (2, BASE, "en", "a", 1), (3, None, None, None, None), (4, "", "de", "b", 0), (5, LONG, "de", "b", 1), (None, BASE, "en", "a", 1), (None, None, None, None, None), (6, " \t\n ", "en", "a", 3), (7, "kurz", "de", "a", 4)]


@pytest.fixture(scope="module")
def rough(spark):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    return docs.select("*", *[F.lit(f"own {c}").alias(c) for c in CLASHES]).cache()


@pytest.fixture(scope="module")
def language(spark):
    return language_crf.fit(["der die das und"] * 3 + ["the and of that"] * 3, ["de"] * 3 + ["en"] * 3)


OPERATORS = {
    "media": lambda d, m: gif.gif_payloads(gif.texts_to_gif(d)),
    "pieces": lambda d, m: pieces.decoded(pieces.encoded(d, pieces.PieceModel.load(pieces.DEFAULT_MODEL)), pieces.PieceModel.load(pieces.DEFAULT_MODEL)),
    "toxicity": lambda d, m: toxicity.scored(d, toxicity.fit(["a b", "c d"], [0, 1])),
    "language": lambda d, m: language_crf.identified(d, m),
    "fingerprints": lambda d, m: fingerprints.with_next(fingerprints.with_shingle_hashes(d, "text", "s"), "doc_id", ["text"]),
    "mixing": lambda d, m: poisson_mix.poisson_mix(d, total=3.0),
    "near_dups": lambda d, m: near_dups.deduplicated(d),
    "windows": lambda d, m: windows.drop_repeats(d),
    "shards": lambda d, m: shards.shards(d.withColumn("size", F.lit(3)).withColumn("key_hash", F.xxhash64("text")), 4),
    "urls": lambda d, m: url_rules.url_verdicts(d.withColumn("url", F.col("text")), d.sparkSession.createDataFrame(url_rules.QUERY_RULES, "host string, path string, verdict string")),
}
SAME_ROWS = {"media", "pieces", "toxicity", "language", "fingerprints", "windows", "shards", "urls"}


@pytest.mark.parametrize("name", OPERATORS)
def test_operator_on_rough_rows(rough, language, name):
    out = OPERATORS[name](rough, language)
    rows = out.collect()
    assert len(set(out.columns)) == len(out.columns)
    if name in SAME_ROWS:
        assert Counter(r["doc_id"] for r in rows) == Counter(r[0] for r in ROWS)
    if name != "media":
        for c in CLASHES:
            assert {r[c] for r in rows} == {f"own {c}"}, c
    assert OPERATORS[name](rough.limit(0), language).isEmpty()


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stage_on_rough_rows(spark, rough, name):
    out = dict(corpus_pipeline.STAGES)[name](spark, rough, SF)
    rows = out.collect()
    assert out.columns[: len(rough.columns)] == rough.columns and all(r["node"] == "own node" for r in rows)
    found = Counter((r["doc_id"], r["text"]) for r in rows)
    if name == "language_id":
        assert found == Counter((r[0], r[1]) for r in ROWS if any(c.isalpha() for c in r[1] or ""))
    if name == "near_dedup":
        assert found == Counter([(1, BASE), (3, None), (4, ""), (5, LONG), (None, BASE), (None, None), (6, " \t\n "), (7, "kurz")])
    if name == "substring_dedup":
        assert found[(2, "")] == 2 and found[(1, BASE)] == 1 and found[(None, "")] == 2 and sum(found.values()) == len(ROWS)
    if name == "mixing":
        assert set(found) <= {(r[0], r[1]) for r in ROWS}
    if name == "pieces":
        assert len(rows) == len(ROWS) and all((r["n_pieces"] == 0) == (not r["text"]) for r in rows)


def test_run_writes_each_stage(spark):
    out = corpus_pipeline.run(spark, SF).collect()
    assert out and {r["doc_id"] for r in out} <= {r["doc_id"] for r in table(spark, SF, "documents").select("doc_id").collect()}


def test_unused_names(spark):
    assert unused(spark.createDataFrame([(1, 2)], "K int, k_ int"), "k", "b") == ("k__", "b")


# --- samples stay bounded ----------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("kind", ["null", "repeated", "own"])
def test_samples_are_bounded(spark, kind):
    i = {"null": F.lit(None).cast("long"), "repeated": F.col("id") % 3 + 1, "own": F.col("id")}[kind]
    docs = spark.range(10_000).select(i.alias("doc_id"), F.concat(F.lit("text "), F.col("id")).alias("text"), F.when(F.col("id") % 100 == 0, "de").otherwise("en").alias("lang"))
    rows = language_crf.training_sample(docs, 60)
    assert 1 <= len(rows) <= 60 and set(rows["lang"]) == {"de", "en"}
    if kind == "own":
        assert len(rows) == 60 and 25 <= (rows["lang"] == "de").sum() <= 35
    labels = docs.select("doc_id", F.when(F.col("lang") == "de", 1).otherwise(0).alias("toxic"))
    found = toxicity.training_sample(docs, labels, 30)
    assert len(found) <= 60 and (kind == "null") == (not len(found))
    assert found["doc_id"].is_unique and (kind != "own" or set(found["toxic"]) == {0, 1})


def test_long_runs_of_letters_are_read_whole():
    run = "漢" * 200 + "the"
    assert "".join(language_crf.words_of(run)) == run and max(map(len, language_crf.words_of(run))) == language_crf.LONGEST_WORD


def test_switched_text_is_labelled_by_word(spark):
    rng = random.Random(1)
    books = {"de": "der die das und nicht haus straße".split(), "en": "the and of that house street with".split(), "fr": "le la les et pas maison rue".split()}
    texts, labels = zip(*[(" ".join(rng.choice(w) for _ in range(30)), lang) for lang, w in books.items() for _ in range(40)], strict=True)
    model = language_crf.fit(list(texts), list(labels))
    assert (model.step[~np.eye(3, dtype=bool)] > -3).all()  # learned from switched texts
    parts = [("de", 9), ("en", 6), ("fr", 12), ("de", 5)]
    text, want = [], []
    for lang, n in parts:
        text += [rng.choice(books[lang]) for _ in range(n)]
        want += [lang] * n
    df = spark.createDataFrame([(1, " ".join(text))], "doc_id long, text string")
    assert [r["lang"] for r in language_crf.word_languages(df, model).orderBy("word_no").collect()] == want
    assert language_crf.identified(df, model).first()["lang_switches"] == 3


def test_toxicity_scores_against_plain_sums(spark):
    model = toxicity.ToxicityModel({"bad": (1.5, 0.5), "badl*": (0.25, 0.0), "fine": (-1.0, -0.5)}, -0.75)

    def plain(text):
        words = Counter("".join(c if c.isalnum() or c == "_" else " " for c in (text or "").lower()).split())
        held = Counter()
        for w, n in words.items():
            for f in [w] + [w[:k] + "*" for k in (4, 5, 6, 7) if len(w) > k]:
                held[f] += n
        z = model.bias
        for f, (there, dense) in model.weights.items():
            z += there * (held[f] > 0) + dense * (held[f] > 1 and held[f] * toxicity.DENSE_WORDS >= words.total())
        return 1 / (1 + np.exp(-z))

    texts = [None, "", "bad", "Bad, bad!", "fine badly badly", "bad " + "x " * 400, "bad bad " + "x " * 400, "é bad\nfine fine"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in toxicity.scored(df, model).collect():
        assert r["score"] == pytest.approx(plain(r["text"])) and r["predicted"] == (r["score"] >= 0.3)


# --- media -------------------------------------------------------------------------------------------------------------------------


def plain_gif(bits=8, stream=None, width=4, height=4):
    stream = gif.lzw_encode(bytes(range(16)), 8) if stream is None else stream
    head = b"GIF89a" + struct.pack("<HHBBB", width, height, 0x70, 0, 0)
    return head + b"," + struct.pack("<HHHHB", 0, 0, width, height, 0) + bytes((bits, len(stream))) + stream + b"\0;"


BROKEN = {
    "code size 9": plain_gif(9), "code size 12": plain_gif(12), "code size 200": plain_gif(200), "code size 0": plain_gif(0), "short stream": plain_gif(stream=gif.lzw_encode(bytes(5), 8)),
    "huge canvas": plain_gif(width=65535, height=65535), "cut file": plain_gif()[:-9], "no stream": plain_gif(stream=b""), "no gif": b"hello", "empty": b"", "first code": plain_gif(stream=b"\xff\xff\xff"),
}


def test_broken_media(spark):
    for data in BROKEN.values():
        with pytest.raises(gif.BrokenImage):
            gif.read_gif(data)
    rows = [(i, 0, bytearray(d)) for i, d in enumerate(BROKEN.values())] + [(90, 0, None), (91, 0, bytearray(plain_gif()))]
    media = spark.createDataFrame(rows, "doc_id long, n_bytes long, media binary")
    assert [r["doc_id"] for r in gif.gif_frames(media).collect()] == [91]
    found = {r["doc_id"]: r["payload"] for r in gif.gif_payloads(media).collect()}
    assert len(found) == len(rows) and [i for i, p in found.items() if p is not None] == [91]


def test_media_query_against_plain_values(spark):
    texts = {r["doc_id"]: r["text"] for r in table(spark, SF, "documents").collect()}
    seen = {}
    for r in gif.op1_gif_media(spark, SF).collect():
        raw = (texts[r["doc_id"]] or "").encode()
        padded = raw + b" " * (max(192, -(-len(raw) // 192) * 192) - len(raw))
        media = gif.payload_gif(padded)
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(raw), len(padded), hashlib.sha256(padded).hexdigest(), zlib.crc32(padded[-16:]))
        assert (r["media_bytes"], r["media_sha256"]) == (len(media), hashlib.sha256(media).hexdigest())
        frames = -(-len(padded) // (192 * 64))
        colours = Counter()
        for f in range(frames):  # a short last image leaves the rows of the one before below it
            shown = padded[f * 12288 : (f + 1) * 12288]
            shown += padded[max(0, f - 1) * 12288 : f * 12288][len(shown) :]
            colours.update(4 * (b >> 7) + 2 * ((b * 7 & 255) >> 7) + (255 - b >> 7) for b in shown)
        assert r["feature"] == f"frames={frames};ms={100 * frames};rgb8={','.join(str(colours[i]) for i in range(8))}"
        assert seen.setdefault(texts[r["doc_id"]], r["feature"]) == r["feature"]


# --- 5 fingerprints: digests and likeness of neighbours -----------------------------------------------------------------------------


def test_fingerprint_values(spark):
    """Sketches against the k smallest of the shingle hashes, likeness against a set version of the same sketches."""
    docs = table(spark, SF, "documents").select("doc_id", "text")
    made = {r["doc_id"]: r["s"] for r in fingerprints.with_shingle_hashes(docs, "text", "s").collect()}
    k = fingerprints.K
    want = {i: sorted(set(s))[:k] for i, s in made.items()}
    order = sorted(made, reverse=True)
    for r in fingerprints.op5_fingerprints(spark, SF).collect():
        i = r["doc_id"]
        own = want[i]
        after = want[order[(order.index(i) + 1) % len(order)]]
        assert r["fingerprint"] == "".join(f"{h & (1 << 64) - 1:016x}" for h in own)
        both = sorted(set(own) | set(after))[:k]
        assert r["near_next"] == pytest.approx(len(set(both) & set(own) & set(after)) / len(both) if both else 1.0)


# --- 8 overfull buckets ------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("standing", [10**6, 300])
def test_overfull_buckets_are_opened_in_blocks(spark, monkeypatch, standing):
    """Nearly all windows share one short run, hence one bucket; results equal brute force with blocks of a few rows."""
    rng = random.Random(8)
    shared = [" ".join(rng.choice(WORDS) for _ in range(30)) for _ in range(3)]
    rows = [(i * 37 % 401, " ".join(("hot hot hot " + rng.choice(shared + [" ".join(rng.choice(WORDS) for _ in range(6))])) for _ in range(6))) for i in range(300)]
    monkeypatch.setattr(windows, "BLOCK_BYTES", 2000)
    monkeypatch.setattr(windows, "CHUNK_BYTES", 3000)
    monkeypatch.setattr(windows, "MOST_STANDING", standing)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in windows.drop_repeats(df).collect()}
    assert got == windows.brute_force(rows)


# --- 6, 9, 10: hot keys, groups, inputs that are no files ----------------------------------------------------------------------------


def test_many_sources_join_like_few(spark):
    docs = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").when(F.col("id") % 7 == 0, None).otherwise(F.concat(F.lit("s"), F.col("id") % 11)).alias("source"))
    few, many = (sorted((r["mix_key"], str(r["source"]), round(r["mix_rate"], 9)) for r in poisson_mix.poisson_mix(docs, broadcast_sources=n).collect()) for n in (100, 2))
    assert few == many and few


@pytest.mark.parametrize("copies", [5, 400])
def test_equal_texts_share_a_shard(spark, copies):
    """Groups under a 64th of a shard stay whole wherever splitters fall, larger ones are dealt by row; compared with a plain version."""
    docs = spark.range(1280 * 5).select(F.col("id").alias("doc_id"), F.concat(F.lit("text number "), F.when(F.col("id") < copies, 0).otherwise(F.col("id") % 1280)).alias("text"))
    sized = shards.document_sizes(docs).withColumn("size", F.col("size").cast("long"))
    rows = [(r["key_hash"], r["doc_id"], r["size"]) for r in sized.collect()]
    got = {r["doc_id"]: (r["shard"], r["slot"]) for r in shards.shards(sized.repartition(5), 16, rows_per_range=40).collect()}
    assert got == shards.reference(rows, 16)


def test_equal_rows_are_no_hot_key(spark):
    docs = spark.range(6000).select(F.when(F.col("id") % 2 == 0, 7).otherwise(F.col("id")).alias("doc_id"), F.when(F.col("id") % 2 == 0, "same").otherwise(F.concat(F.lit("t"), F.col("id"))).alias("text"))
    out = shards.shards(shards.document_sizes(docs), 8).collect()
    sums = Counter()
    for r in out:
        sums[r["shard"]] += r["size"]
    assert len(out) == 6000 and max(sums.values()) - min(sums.values()) <= 0.05 * max(sums.values())
    for s in sums:
        assert sorted(r["slot"] for r in out if r["shard"] == s) == list(range(sum(r["shard"] == s for r in out)))


def test_shard_documents_writes_repeated_rows(spark, rough, tmp_path):
    shards.shard_documents(rough, str(tmp_path / "out"), 4)
    assert Counter(r["doc_id"] for r in spark.read.parquet(str(tmp_path / "out")).collect()) == Counter(r[0] for r in ROWS)


def plain_verdict(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = rest
    for c in "/?#":
        host = host.split(c, 1)[0]
    path = rest[len(host) :].split("?", 1)[0].split("#", 1)[0]
    host = host.lower()
    fits = [(len(h + p), h + p, v) for h, p, v in url_rules.QUERY_RULES if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[1:] if fits else (None, "allow")))


@pytest.mark.parametrize("most", [url_rules.BROADCAST_BYTES, 0])
@pytest.mark.parametrize("shape", ["repartition", "union", "aggregate"])
def test_url_verdicts_belong_to_their_rows(spark, monkeypatch, shape, most):
    monkeypatch.setattr(url_rules, "BROADCAST_BYTES", most)
    hosts = F.array(*[F.lit(h) for h in ("example.org", "www.example.org", "shop.com", "a.b.com", "none.net", "ORG")])
    paths = F.array(*[F.lit(p) for p in ("/es/", "/en/1", "/fr/", "/de/", "/", "")])
    url = F.concat(F.lit("http://"), F.get(hosts, (F.col("id") % 6).cast("int")), F.get(paths, (F.col("id") / 7 % 6).cast("int")), (F.col("id") % 50).cast("string"))
    pages = spark.range(20_000).select(F.col("id").alias("page_id"), F.when(F.col("id") % 3 > 0, url).alias("url"))
    pages = {"repartition": lambda: pages.repartition(7), "union": lambda: pages.where("page_id < 9000").union(pages.where("page_id >= 9000").repartition(3)), "aggregate": lambda: pages.groupBy("page_id").agg(F.max("url").alias("url"))}[shape]()
    rules = spark.createDataFrame(url_rules.QUERY_RULES, "host string, path string, verdict string")
    rows = url_rules.url_verdicts(pages, rules).collect()
    assert len(rows) == 20_000 and len({r["page_id"] for r in rows}) == 20_000
    known = {}
    for r in rows:
        want = known.get(r["url"]) or known.setdefault(r["url"], plain_verdict(r["url"]))
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == want
