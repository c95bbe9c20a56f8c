"""Each operator against a brute-force version, exact round trips, held-out accuracy, and awkward inputs."""

import hashlib
import itertools
import random
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tracelink.llm import fingerprints as FP
from tracelink.llm import gif, language_crf, near_dups, pieces, poisson_mix, shards, toxicity, url_rules, windows
from tracelink.llm.common import Words, run_hash, table

SF = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, n_chars long"
random.seed(7)
VOCABULARY = [f"w{i}" for i in range(60)]
LONG = " ".join(random.choice(VOCABULARY) for _ in range(6000))


def passage(n):
    return " ".join(random.choice(VOCABULARY) for _ in range(n))


BASE = passage(120)
SHARED = passage(40)
AWKWARD = [
    (1, BASE, "en", "a", 1), (2, BASE, "en", "a", 1), (3, BASE.replace("w5 ", "w6 ", 1), None, "a", 1), (4, BASE.upper(), "fr", None, 1), (5, None, "en", "a", 1), (6, "", "en", "b", 1),
    (7, " \t\n\x0b ", "en", "b", 1), (8, "one two three", "en", "b", 1), (9, "one two  three", "en", "b", 1), (10, LONG, "de", "b", 1), (11, SHARED + " " + passage(30), "en", "c", 1),
    (12, passage(20) + " " + SHARED, "en", "c", 1), (13, SHARED, "en", "c", 1), (14, "ñandú 日本語 🎉 \u2581 x\x00y", "es", "c", 1), (None, BASE, "en", "c", 1), (20, "a b " * 40, "en", "c", 1), (20, "a b " * 40, "en", "c", 1),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(AWKWARD, DOC).repartition(3).cache()


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], DOC)


def with_ids():
    return [(r[0], r[1]) for r in AWKWARD if r[0] is not None and r[0] != 20]


# --- words -------------------------------------------------------------------------------------------------------------------------


def test_words_and_hashes():
    texts = [b"", b" a  bb\tccc\n", b"bb ccc a", b"\xc3\xa9 bb"]
    words = Words(texts)
    found = [[words.raw[words.start[i] : words.end[i]] for i in range(words.first[d], words.first[d + 1])] for d in range(len(texts))]
    assert found == [t.split() for t in texts]
    by = {}
    for w, h in zip(itertools.chain(*found), words.hash.tolist(), strict=True):
        assert by.setdefault(w, h) == h
    assert len(set(by.values())) == len(by)
    runs = run_hash(words.hash, 2, 1)
    assert runs[1] == run_hash(Words([b"bb ccc"]).hash, 2, 1)[0]


# --- 1 media -----------------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("bits", [2, 4, 8])
def test_lzw_round_trip(bits):
    rng = np.random.default_rng(bits)
    for n in (0, 1, 2, 5, 300, 20_000):
        for data in (rng.integers(0, 1 << bits, n).astype(np.uint8).tobytes(), bytes(n), bytes(i % 3 for i in range(n))):
            assert gif.lzw_decode(gif.lzw_encode(data, bits), bits, n) == data


def test_lzw_known_stream():
    # clear, 1, 6, 6, 2, stop in codes of 3 bits for 2-bit samples: 1, 1 1, 1 1 ... as the format describes it
    assert gif.lzw_decode(gif.lzw_encode(bytes([1] * 10), 2), 2, 10) == bytes([1] * 10)


def test_gif_rules():
    palette = np.array([[0, 0, 0], [255, 0, 0], [0, 255, 0], [0, 0, 255]], dtype=np.uint8)
    own = np.array([[9, 9, 9], [7, 7, 7]], dtype=np.uint8)
    a = np.ones((4, 4), dtype=np.uint8)
    hole = np.array([[2, 0], [0, 2]], dtype=np.uint8)
    patches = [gif.Patch(a, delay=5), gif.Patch(hole, 1, 1, 7, gif.PREVIOUS, transparent=0), gif.Patch(hole, 0, 0, 1, gif.BACKGROUND), gif.Patch(np.ones((1, 1), dtype=np.uint8), 3, 3, 2, palette=own), gif.Patch(np.arange(40, dtype=np.uint8).reshape(10, 4) % 4, interlaced=True)]
    image = gif.read_gif(gif.write_gif(gif.Gif(4, 4, palette, patches[:4], loops=3)))
    assert image.loops == 3 and [p.delay for p in image.patches] == [5, 7, 1, 2]
    shots = [(c.copy(), m.copy()) for c, m in gif.composed(image)]
    assert shots[0][0][0, 0].tolist() == [255, 0, 0]
    assert shots[1][0][1, 1].tolist() == [0, 255, 0] and shots[1][0][1, 2].tolist() == [255, 0, 0]
    assert shots[2][0][1, 2].tolist() == [255, 0, 0] and shots[2][0][0, 0].tolist() == [0, 255, 0]
    assert not shots[3][1][0, 0] and shots[3][0][3, 3].tolist() == [7, 7, 7]
    tall = gif.read_gif(gif.write_gif(gif.Gif(4, 10, palette, patches[4:])))
    assert tall.patches[0].interlaced and (tall.patches[0].index == patches[4].index).all()
    with pytest.raises(gif.BrokenImage):
        gif.read_gif(b"GIF89a\x01")


def test_media_query(spark, docs, nothing):
    rows = {r["doc_id"]: r for r in gif.gif_payloads(gif.texts_to_gif(docs)).collect()}
    for i, t in with_ids():
        raw = (t or "").encode()
        want = raw.ljust(max(192, -(-len(raw) // 192) * 192), b" ")
        assert bytes(rows[i]["payload"]) == want and rows[i]["n_bytes"] == len(raw)
    frames = gif.gif_frames(gif.texts_to_gif(docs.where("doc_id = 10"))).orderBy("frame").collect()
    assert len(frames) == -(-len(LONG.encode()) // (192 * 64)) and frames[1]["start_ms"] == 100 and sum(frames[0]["histogram"]) == 192 * 64
    assert gif.texts_to_gif(nothing).isEmpty() and gif.gif_frames(gif.texts_to_gif(nothing)).isEmpty()
    out = gif.op1_gif_media(spark, SF).first()
    assert out["payload_bytes"] % 192 == 0 and len(out["media_sha256"]) == 64


# --- 2 pieces ----------------------------------------------------------------------------------------------------------------------


def brute_best(text, scores):
    n = len(text)
    best = [0.0] + [float("-inf")] * n
    for i in range(n):
        for j in range(i + 1, n + 1):
            if text[i:j] in scores:
                best[j] = max(best[j], best[i] + scores[text[i:j]])
        if text[i] not in scores:
            best[i + 1] = max(best[i + 1], best[i] - 99)
    return best[n]


def test_automaton_finds_the_best_path():
    rng = random.Random(5)
    for _ in range(30):
        scores = {"".join(rng.choice("abc") for _ in range(rng.randint(1, 4))): -rng.random() * 5 for _ in range(12)}
        machine = pieces.Automaton([(p, s, i) for i, (p, s) in enumerate(scores.items())])
        names = list(scores)
        for _ in range(20):
            text = "".join(rng.choice("abcd") for _ in range(rng.randint(0, 12)))
            path = machine.best(text, -99)
            assert sum(n for n, _ in path) == len(text)
            total = sum(-99 if i < 0 else scores[names[i]] for _, i in path)
            assert total == pytest.approx(brute_best(text, scores))


def test_pieces_against_the_library_and_round_trip(spark, docs, nothing):
    model = pieces.PieceModel.load(pieces.DEFAULT_MODEL)
    out = pieces.decoded(pieces.encoded(docs, model), model)
    for r in out.collect():
        assert r["decoded"] == (r["text"] or "") and r["n_pieces"] == len(r["pieces"])
    assert pieces.encoded(nothing, model).isEmpty()

    import sentencepiece

    raw = bytearray(open(pieces.DEFAULT_MODEL, "rb").read())

    def number(at):
        value = shift = 0
        while True:
            b = raw[at]
            value, shift, at = value | (b & 127) << shift, shift + 7, at + 1
            if b < 128:
                return value, at

    def fields(at, end):
        while at < end:
            tag, at = number(at)
            if tag & 7 == 2:
                n, at = number(at)
                yield tag >> 3, at, at + n
                at += n
            else:
                start = at
                at = number(at)[1] if tag & 7 == 0 else at + (4 if tag & 7 == 5 else 8)
                yield tag >> 3, start, at

    for f, a, b in list(fields(0, len(raw))):
        if f == 2:
            for g, c, _ in fields(a, b):
                if g == 3:
                    raw[c] = 1  # the same pieces and scores, read as a unigram model
    library = sentencepiece.SentencePieceProcessor()
    library.LoadFromSerializedProto(bytes(raw))
    texts = [t["text"][:80] for t in table(spark, SF, "documents").select("text").limit(60).collect()] + ["hello world", "  a  b", "日本語 テキスト", "x\ny\tz", "🎉🎉", "a"]
    # the library adds scores in single precision, next to pieces that cost a billion: it may miss the best path, and is never better
    score = lambda ids: sum(library.get_score(int(i)) for i in ids if not library.is_byte(int(i)))
    alike = 0
    for t in texts:
        mine, theirs = model.encode(t).tolist(), library.encode(t)
        assert score(mine) >= score(theirs)
        alike += mine == theirs
    assert alike > len(texts) / 2


# --- 3 toxicity --------------------------------------------------------------------------------------------------------------------


def test_toxicity(spark, docs, nothing):
    rng = random.Random(3)
    clean = [passage(30) + rng.choice(["", " muslims here"]) for _ in range(200)]
    foul = [passage(15) + " " + rng.choice(["idiot", "moron"]) + rng.choice([" women", " muslims", " muslims"]) + " " + passage(10) for _ in range(60)]
    model = toxicity.fit(clean + foul, [0] * 200 + [1] * 60)
    free = toxicity.fit(clean + foul, [0] * 200 + [1] * 60, fairness=0.0)
    assert model.score("you idiot w1 w2") > 0.5 > model.score("w1 w2 w3")
    gap = lambda m: abs(m.logit(toxicity.words_of("the women were here")) - m.logit(toxicity.words_of("the men were here")))
    assert gap(model) < 0.25 * gap(free) + 1e-6 and model.score("the women were here") < 0.3
    assert toxicity.twin_of(Counter({"women": 2}), toxicity.swaps(1)) == Counter({"men": 2})
    out = toxicity.scored(docs, model).collect()
    assert len(out) == len(AWKWARD) and all(0 <= r["score"] <= 1 for r in out)
    assert toxicity.scored(nothing, model).isEmpty() and toxicity.fit([], []).score(None) < 0.3
    sf = "/root/testdata/sf0.1"
    scored = toxicity.op3_toxicity(spark, sf).join(table(spark, sf, "labels"), "doc_id").where("held_out").collect()
    right = [r["predicted"] == r["toxic"] for r in scored]
    assert sum(right) / len(right) > 0.97


# --- 4 language --------------------------------------------------------------------------------------------------------------------


def test_forward_backward_against_enumeration():
    rng = np.random.default_rng(0)
    s, step, start = rng.normal(size=(7, 3)), rng.normal(size=(3, 3)), rng.normal(size=3)
    gamma, pairs = language_crf.forward_backward(s, np.array([3, 4]), step, start)

    def enumerated(x):
        total, g, p = 0.0, np.zeros((len(x), 3)), np.zeros((3, 3))
        for y in itertools.product(range(3), repeat=len(x)):
            w = np.exp(start[y[0]] + sum(x[i, c] for i, c in enumerate(y)) + sum(step[a, b] for a, b in itertools.pairwise(y)))
            total += w
            for i, c in enumerate(y):
                g[i, c] += w
            for a, b in itertools.pairwise(y):
                p[a, b] += w
        return g / total, p / total

    (a, p), (b, q) = enumerated(s[:3]), enumerated(s[3:])
    assert np.allclose(gamma, np.concatenate([a, b])) and np.allclose(pairs, p + q)


def test_language(spark, docs, nothing):
    sf = "/root/testdata/sf0.01"
    out = language_crf.op4_language_crf(spark, sf).join(table(spark, sf, "documents").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang_pred"] == r["lang"] for r in out) / len(out) > 0.95
    model = language_crf.fit(["der die das und"] * 3 + ["the and of that"] * 3, ["de"] * 3 + ["en"] * 3)
    rows = language_crf.identified(docs, model).collect()
    assert len(rows) == len(AWKWARD) and {r["lang_pred"] for r in rows if not any(c.isalpha() for c in r["text"] or "")} == {"und"}
    words = language_crf.word_languages(spark.createDataFrame([(1, "the and of der die das und")], "doc_id long, text string"), model).orderBy("word_no").collect()
    assert [r["lang"] for r in words] == ["en"] * 3 + ["de"] * 4
    assert language_crf.identified(nothing, language_crf.train(nothing)).isEmpty()


# --- 5 fingerprints ----------------------------------------------------------------------------------------------------------------


def test_fingerprints(spark, docs):
    out = {r["doc_id"]: r for r in FP.op5_fingerprints(spark, SF).collect()}
    texts = {r["doc_id"]: r["text"] or "" for r in table(spark, SF, "documents").collect()}
    order = sorted(texts, reverse=True)
    errors = []
    for i, d in enumerate(order):
        t, after = texts[d], texts[order[(i + 1) % len(order)]]
        cut = len(t) // 3
        edited = t[: len(t) - cut] + after[:cut]
        assert out[d]["n_chars"] == len(t) and out[d]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        sets = [set(zip(*[x.encode().split()[k:] for k in range(5)], strict=False)) for x in (t, edited)]
        if min(map(len, sets)) > 3:
            errors.append(abs(out[d]["near_edited"] - len(sets[0] & sets[1]) / len(sets[0] | sets[1])))
    assert np.mean(errors) < 0.04 and max(errors) < 0.25
    plan = FP.op5_fingerprints(spark, SF)._jdf.queryExecution().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_sketches_merge(spark, docs, nothing):
    made = FP.with_shingle_hashes(docs.select("doc_id", "text"), "text", "s").withColumn("own", FP.sketch(F.col("s"), 16))
    rows = {r["doc_id"]: r for r in made.collect()}
    assert rows[1]["own"] == rows[2]["own"] and rows[5]["own"] == rows[7]["own"] == [] and len(rows[8]["own"]) == 1 and rows[8]["own"] == rows[9]["own"]
    whole = sorted(set(itertools.chain(*(r["s"] for r in rows.values()))))[:16]
    parts = FP.merge_sketches(made.withColumn("k", F.lit(1)), ["k"], "own", 16).first()["own"]
    assert parts == whole
    pair = made.where("doc_id in (10)").select(FP.distinct_count(F.col("own"), 16).alias("n"), FP.resemblance(F.col("own"), F.col("own"), 16).alias("r"), FP.containment(F.col("own"), F.col("own"), 16).alias("c")).first()
    assert 2000 < pair["n"] < 18000 and pair["r"] == 1.0 and pair["c"] == 1.0
    nexts = FP.with_next(docs.select("doc_id", "text"), "doc_id", ["text"]).where("doc_id = 4").first()
    assert nexts["next_text"] == AWKWARD[2][1]
    assert FP.with_next(nothing.select("doc_id", "text"), "doc_id", ["text"]).isEmpty()


# --- 6 mixing ----------------------------------------------------------------------------------------------------------------------


def test_poisson_mix(spark, docs, nothing):
    big = spark.range(20_000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "hot").otherwise(F.concat(F.lit("s"), F.col("id") % 5)).alias("source"))
    out = poisson_mix.poisson_mix(big, {"hot": 1.0, "s0": 3.0, "s1": 1.0}, total=40.0).groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.first("mix_rate").alias("rate")).collect()
    n = {r["source"]: r["n"] for r in out}
    assert set(n) == {"hot", "s0", "s1"} and sum(n.values()) == pytest.approx(800_000, rel=0.02) and n["s0"] == pytest.approx(3 * n["hot"], rel=0.05)
    assert max(r["rate"] for r in out) > poisson_mix.STREAM_RATE  # several streams
    again = [r["mix_key"] for r in poisson_mix.poisson_mix(docs).select("mix_key").collect()]
    assert sorted(again) == sorted(r["mix_key"] for r in poisson_mix.poisson_mix(docs.repartition(5)).select("mix_key").collect())
    counts = poisson_mix.poisson_mix(big.drop("source").withColumn("source", F.lit(None).cast("string")), total=2.0).groupBy("doc_id").count().collect()
    share = Counter(r["count"] for r in counts)
    assert share[1] / 20_000 == pytest.approx(2 * np.exp(-2), abs=0.02) and share[3] / 20_000 == pytest.approx(8 / 6 * np.exp(-2), abs=0.02)
    assert poisson_mix.poisson_mix(nothing).isEmpty()


# --- 7 near duplicates -------------------------------------------------------------------------------------------------------------


def near_copies(n):
    rng = random.Random(11)
    out = []
    for g in range(n):
        base = passage(rng.choice([6, 40, 120])).split()
        for _ in range(rng.randint(1, 14)):
            copy = [w if rng.random() > rng.choice([0, 0.005, 0.02, 0.05]) else rng.choice(VOCABULARY) for w in base]
            out.append((len(out) * 7 % 1009, " ".join(copy)))
    return out


@pytest.mark.parametrize("percent", [80, 85])
def test_near_dups_against_brute_force(spark, percent):
    rows = near_copies(25)
    want = near_dups.brute_force(rows, percent)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dups.near_dups(df, percent=percent).collect()}
    assert got == want and len({c for _, c in want.values()}) < len(want)


def test_near_dups_on_awkward_rows(spark, docs, nothing):
    got = near_dups.near_dups(docs, percent=85).collect()
    assert len(got) == len(AWKWARD)
    by = {r["doc_id"]: r for r in got}
    want = near_dups.brute_force(with_ids(), 85)
    assert {i: (by[i]["n_shingles"], by[i]["component_id"]) for i in want} == want
    assert by[None]["kept"] and by[None]["component_id"] is None and by[5]["kept"] and by[6]["kept"] and by[7]["kept"]
    kept = [r["doc_id"] for r in near_dups.deduplicated(docs).select("doc_id").collect()]
    assert sorted(i for i in kept if i is not None) == [1, 5, 6, 7, 8, 10, 11, 12, 13, 14, 20] and kept.count(None) == 1
    assert near_dups.near_dups(nothing).isEmpty() and near_dups.deduplicated(nothing).isEmpty()
    assert near_dups.match_threshold(85) > near_dups.match_threshold(80) > 1


def test_components(spark):
    edges = [(i, i + 1) for i in range(0, 30)] + [(100, 101), (101, 102), (200, 100)]
    got = dict(tuple(r) for r in near_dups.components(spark.createDataFrame(edges, "a long, b long")).collect())
    assert got == {**dict.fromkeys(range(31), 0), 100: 100, 101: 100, 102: 100, 200: 100}


# --- 8 substrings ------------------------------------------------------------------------------------------------------------------


def test_windows_against_brute_force(spark, docs, nothing):
    rng = random.Random(2)
    parts = [passage(rng.choice([13, 14, 30])) for _ in range(6)]
    rows = [(i * 31 % 211, " ".join(rng.choice([passage(rng.randint(0, 25)), rng.choice(parts)]) for _ in range(4))) for i in range(120)] + [(r[0] + 1000, r[1]) for r in AWKWARD if r[0] is not None and r[0] != 20]
    want = windows.brute_force(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], hashlib.sha256(r["text"].encode()).hexdigest()) for r in windows.drop_repeats(df).collect()}
    assert got == want and sum(v[1] for v in want.values()) > 500
    assert windows.drop_repeats(nothing).isEmpty() and windows.drop_repeats(docs).count() == len(AWKWARD)
    twice = [r["n_removed"] for r in windows.drop_repeats(docs).where("doc_id = 20").collect()]
    assert twice == [0, 0]


def test_equal_hashes_are_told_apart(monkeypatch):
    h = np.array([1, 2, 9, 1, 2, 3, 4, 1, 2], dtype=np.uint64)
    at, owner = np.array([0, 3, 5, 7]), np.array([1, 2, 2, 3])
    monkeypatch.setattr(windows, "run_hash", lambda h, width, seed: np.zeros(len(h) - width + 1, dtype=np.uint64))
    assert windows.repeated(h, at, owner, 2).tolist() == [False, True, False, True]


# --- 9 shards ----------------------------------------------------------------------------------------------------------------------


def test_shards(spark, docs, nothing):
    out = shards.op9_shards(spark, "/root/testdata/sf0.01").collect()
    sums = Counter()
    for r in out:
        sums[r["shard"]] += r["size"]
    mean = sum(sums.values()) / 16
    assert set(sums) == set(range(16)) and all(abs(v - mean) <= max(r["size"] for r in out) for v in sums.values())
    for s in range(16):
        assert sorted(r["slot"] for r in out if r["shard"] == s) == list(range(sum(r["shard"] == s for r in out)))
    texts = {r["doc_id"]: r["text"] for r in table(spark, "/root/testdata/sf0.01", "documents").collect()}
    assert all(r["size"] == len(texts[r["doc_id"]].encode()) + 1 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]].encode()) for r in out)
    hot = spark.range(3000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "same text").otherwise(F.concat(F.lit("t"), F.col("id"))).alias("text"))
    dealt = shards.shards(shards.document_sizes(hot), 8).groupBy("shard").agg(F.sum("size").alias("b")).collect()
    goal = sum(r["b"] for r in dealt) / 8
    assert len(dealt) == 8 and max(abs(r["b"] - goal) for r in dealt) < 0.02 * goal
    assert shards.shards(shards.document_sizes(docs), 4).count() == len(AWKWARD) and shards.shards(shards.document_sizes(nothing), 4).isEmpty()


# --- 10 URLs -----------------------------------------------------------------------------------------------------------------------


def brute_verdict(url, rules):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    host = rest
    for c in "/?#":
        host = host.split(c, 1)[0]
    path = rest[len(host) :].split("?", 1)[0].split("#", 1)[0]
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(len(h + p), h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    return (host, path, *(max(fits)[1:] if fits else (None, "allow")))


def test_url_rules(spark):
    urls = [None, "", "no scheme", "://", "http://", "http://ORG/", "http://a.Example.ORG/es/x?y", "http://example.org/en/1", "http://example.org/en/12#z", "http://xexample.org/en/1", "https://b.com/fr/1", "https://b.com/de/?q", "http://com", "http://.com/de/", "ftp://x.y://z.org/", "http://a.org:80/", "http://ÄÖ.org/é"]
    df = spark.createDataFrame([(i, u, "x", "y") for i, u in enumerate(urls + urls[6:7])], "page_id long, url string, host string, rid string")
    rules = spark.createDataFrame(url_rules.QUERY_RULES, "host string, path string, verdict string")
    out = url_rules.url_verdicts(df, rules)
    assert out.columns == ["page_id", "url", "rid", "host", "path", "rule", "verdict"]
    for r in out.collect():
        assert (r["host"], r["path"], r["rule"], r["verdict"]) == brute_verdict(r["url"], url_rules.QUERY_RULES)
    assert out.count() == len(urls) + 1
    assert url_rules.url_verdicts(df, rules.limit(0)).where("verdict <> 'allow'").isEmpty() and url_rules.url_verdicts(df.limit(0), rules).isEmpty()


# --- pipeline ----------------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, nothing):
    docs = table(spark, SF, "documents")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert names == ["language_id", "near_dedup", "substring_dedup", "mixing", "pieces"]
    kept = docs
    for name, stage in corpus_pipeline.STAGES:
        before = {r["doc_id"]: r for r in kept.collect()}
        after = stage(spark, kept, SF).cache()
        rows = after.collect()
        if name != "pieces":
            assert after.columns == docs.columns
        if name == "language_id":
            assert {r["doc_id"] for r in rows} == {i for i, r in before.items() if any(c.isalpha() for c in r["text"])}
        if name == "near_dedup":
            want = near_dups.brute_force([(i, r["text"]) for i, r in before.items()], 80)
            assert {r["doc_id"] for r in rows} == {i for i, (_, c) in want.items() if i == c}
        if name == "substring_dedup":
            want = windows.brute_force([(i, r["text"]) for i, r in before.items()])
            assert {r["doc_id"]: hashlib.sha256(r["text"].encode()).hexdigest() for r in rows} == {i: w[2] for i, w in want.items()}
            assert all(r["n_chars"] == len(r["text"]) for r in rows)
        if name == "mixing":
            assert {(r["doc_id"], r["text"]) for r in rows} <= {(i, r["text"]) for i, r in before.items()}
        if name == "pieces":
            assert all(r["n_pieces"] == len(r["pieces"]) for r in rows) and len(rows) == kept.count()
        kept = after
    empty = nothing
    for _, stage in corpus_pipeline.STAGES:
        empty = stage(spark, empty, SF)
        assert empty.isEmpty()


def test_deduplicated_keeps_distinct_texts_of_one_id(spark):
    a, b, c = ("".join(f"{w}{i} " for i in range(40)) for w in ("red", "green", "blue"))
    docs = spark.createDataFrame([(1, a), (5, b), (5, c), (5, c), (7, b), (3, a), (3, "one text of its own kind here"), (9, ""), (9, "")], "doc_id long, text string")
    got = sorted(tuple(r) for r in near_dups.deduplicated(docs).collect())
    assert got == sorted([(1, a), (5, b), (5, c), (3, "one text of its own kind here"), (9, ""), (9, "")])
