import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

pytest.importorskip("allpairs.llm")
from allpairs.llm import fingerprints, heavy_light, language, media, packing, personal_data, pieces, sharding, token_files, tokens, toxicity  # noqa: E402
from allpairs.llm import queries as Q  # noqa: E402

SF = "/root/testdata/sf0.001"
ODD = [
    (1, "The cat sat. On the mat it sat, and sat again all day long."),
    (2, None),
    (3, ""),
    (4, "  \n\t "),
    (5, "The cat sat. On the mat it sat, and sat again all day long."),
    (6, "Ünïcödé ﬁne ＴＥＸＴ  日本語 😀 mail me at a.b@c.example.org_x@d.ef or +1 (677) 555-7033 now"),
    (7, "word " * 9000),
    (8, "0.0.0.256 1.2.3.4 12.34.56.78.90 4917085256960696 4111 1111 1111 1111 1-2-3 (212) 555-0199 password=e3b3ed3cc8548923d6"),
    (None, "a row without id"),
    (9, "x" * 5000),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(d, t, "en", "s", None, 1) for d, t in ODD], "doc_id long, text string, lang string, source string, n_chars long, n long").cache()


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_shards_equal_sizes_no_gaps_and_recomputed_places(spark, odd):
    for n in (1, 2, 3, 40):
        got = rows(sharding.shard(odd, n))
        slots = {}
        for r in got:
            slots.setdefault(r["shard"], []).append(r["slot"])
        assert all(sorted(s) == list(range(len(s))) for s in slots.values())
        sizes = [len(slots.get(k, [])) for k in range(n)]
        assert max(sizes) - min(sizes) <= 1 and len(got) == len(ODD)
    assert sharding.shard(odd.limit(0)).count() == 0
    for n in (1, 2, 5, 97, 1000):
        placed = sharding.permuted_rows(spark.range(n).select(F.col("id").alias("row"), F.lit(n).cast("long").alias("n_rows")))
        assert sorted(r["place"] for r in placed.collect()) == list(range(n))
    a = rows(sharding.shard(odd))
    assert {(r["doc_id"], r["shard"], r["slot"]) for r in a} == {(r["doc_id"], r["shard"], r["slot"]) for r in rows(sharding.shard(odd.repartition(7)))}
    texts = dict(ODD)
    assert all(r["text_crc32"] == zlib.crc32((texts[r["doc_id"]] or "").encode()) and r["size"] == len((texts[r["doc_id"]] or "").encode()) + 16 for r in a)


def test_fingerprints_by_brute_force(spark, odd):
    import unicodedata

    def canon(t):
        return " ".join(re.split(r"[\s\x1c-\x1f\x85]+", unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t).casefold())))

    docs = sorted(((d, t or "") for d, t in ODD), key=lambda x: (x[0] is not None, x[0] or 0))
    for wide in (fingerprints.digest, lambda c: F.substring(fingerprints.digest(c), 1, 1)):
        got = {r["doc_id"]: r for r in rows(fingerprints.fingerprints(odd, wide=wide))}
        assert len(got) == len(docs)
        for k, (d, t) in enumerate(docs):
            after = docs[(k + 1) % len(docs)][1]
            quarter = len(t) // 4
            edited = t[: len(t) - quarter] + after[:quarter]
            assert got[d]["n_chars"] == len(t) and got[d]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        for d, t in docs:
            for e, u in docs:
                assert (got[d]["fp"] == got[e]["fp"]) == (canon(t).strip() == canon(u).strip()), (d, e)
    assert fingerprints.fingerprints(odd.limit(0)).count() == 0


def test_fingerprints_across_ranges(spark, monkeypatch):
    monkeypatch.setattr(fingerprints, "BUCKET_ROWS", 7)
    docs = spark.range(100).select(F.col("id").alias("doc_id"), F.concat(F.lit("text number "), (F.col("id") * 7919 % 100).cast("string")).alias("text"))
    got = {r["doc_id"]: r["next_text"] for r in fingerprints.with_next(docs).collect()}
    assert got == {k: f"text number {(k + 1) % 100 * 7919 % 100}" for k in range(100)}


BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def base_spans(text):
    def luhn(d):
        return sum(sum(divmod(2 * int(c), 10)) if k % 2 else int(c) for k, c in enumerate(reversed(d))) % 10 == 0

    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(p) <= 255 for p in m[0].split(".")) if kind == "ip" else True, "card": 16 <= len(digits) <= 19 and luhn(digits), "phone": 8 <= len(digits) <= 15}[kind]
            if ok:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_personal_data_by_brute_force(spark, odd):
    rng = random.Random(3)
    made = ["".join(rng.choice("ab1.@+-_ ()4") for _ in range(rng.randint(0, 60))) for _ in range(400)] + ["1 " * 3000, "9" * 6000, "a@b.c_d@e.f@g.hh x@y.z"]
    docs = spark.createDataFrame(list(enumerate(made, 100)), "doc_id long, text string").unionByName(odd.select("doc_id", "text"))
    texts = {**dict(enumerate(made, 100)), **dict(ODD)}
    found, model = personal_data.find(docs)
    base = found.select("doc_id", personal_data.described(F.filter("spans", lambda s: s["base"])).alias("b"), personal_data.described(F.col("spans")).alias("all"))
    for r in rows(base):
        assert r["b"] == base_spans(texts[r["doc_id"]] or ""), texts[r["doc_id"]]
        assert set(filter(None, r["b"].split(","))) <= set(r["all"].split(","))
    assert "secret:" in next(r["all"] for r in rows(base) if r["doc_id"] == 8)
    clean = found.join(docs, "doc_id").select("doc_id", personal_data.redact(F.coalesce("text", F.lit("")), F.col("spans")).alias("t")).filter("doc_id = 6").first()["t"]
    assert "<EMAIL>" in clean and "<PHONE>" in clean and "555" not in clean
    assert personal_data.find(docs.limit(0))[0].count() == 0
    assert all(0.5 < x < 1 for v in model.reliability.values() for x in v)


def test_long_secrets_are_redacted_whole(spark):
    rng = random.Random(5)
    made = lambda n: "".join(rng.choice("abcXYZ0189") for _ in range(n))
    keys = [f"{p}{made(n)}" for p in ("token=", "password: '", "sk_live_", "xoxp-", "AKIA") for n in (8, 12, 64, 65, 128, 129, 300, 20000)]
    keys = [k for k in keys if "=" in k or ":" in k or len(k) > 16]
    docs = spark.createDataFrame([(i, f"the key is {k} and more") for i, k in enumerate(keys)], "doc_id long, text string")
    found, _ = personal_data.find(docs, carry=("doc_id", "text"), threshold=0.0)
    got = {r["doc_id"]: r["t"] for r in found.select("doc_id", personal_data.redact(F.col("text"), F.col("spans")).alias("t")).collect()}
    assert got == {i: "the key is <SECRET> and more" for i in range(len(keys))}


def brute_components(docs, k, num, den):
    fold = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
    sets = {}
    for d, t in docs:
        w = re.findall(rb"[^\x20\x09-\x0D]+", (t or "").encode().translate(fold))
        sets[d] = frozenset(tuple(w[j : j + k]) for j in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            o = len(sets[a] & sets[b])
            if o and den * o >= num * (len(sets[a]) + len(sets[b]) - o):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(s), root(d)) for d, s in sets.items()}


def near_copies(seed, n, longest):
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(60)}"
    texts = []
    for k in range(n):
        if texts and rng.random() < 0.7:
            w = rng.choice(texts).split()
            for _ in range(rng.randint(0, 2)):
                at = rng.randrange(len(w) + 1)
                w[at : at + rng.randint(0, 1)] = [word() for _ in range(rng.randint(0, 1))]
        else:
            w = [word() for _ in range(rng.randint(0, longest))]
        texts.append(" ".join(w))
    return list(enumerate(texts))


@pytest.mark.parametrize("k,num,den,longest,boundary", [(3, 9, 10, 60, None), (3, 9, 10, 20, 14), (5, 4, 5, 50, None), (2, 4, 5, 12, 9), (3, 9, 10, 24, 0)])
def test_jaccard_join_by_brute_force(spark, k, num, den, longest, boundary):
    docs = near_copies(k * longest, 150, longest)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in heavy_light.join(df, k, heavy_light.Similarity(num, den), boundary=boundary).collect()}
    assert got == brute_components(docs, k, num, den)


def test_jaccard_join_counts_links_by_brute_force(spark, monkeypatch):
    monkeypatch.setattr(heavy_light, "BLOCK", 7)
    docs = near_copies(11, 120, 40)
    docs += [(1000 + d, t) for d, t in docs[:30]] + [(None, docs[5][1])]
    sets = []
    for d, t in docs:
        w = t.split()
        sets.append((d, {tuple(w[j : j + 3]) for j in range(len(w) - 2)} or ({tuple(w)} if w else set())))
    want = sorted((d or -1, sum(i != j and len(x & y) * 5 >= 4 * len(x | y) > 0 for j, (_, y) in enumerate(sets))) for i, (d, x) in enumerate(sets))
    found = heavy_light.join(spark.createDataFrame(docs, "doc_id long, text string"), 3, heavy_light.Similarity(4, 5), links=True)
    assert sorted((r["doc_id"] or -1, r["n_links"]) for r in found.collect()) == want and max(n for _, n in want) > 7


def test_jaccard_join_ships_no_texts(spark):
    """Long words make large texts of few shingles; what is left over is too large for Spark to broadcast by itself."""
    from allpairs.counters import counted

    rng = random.Random(6)
    docs = [(d, " ".join("".join(rng.choices("abcdefghijklmnopqrstuvwxyz0123456789", k=400)) for _ in range(20))) for d in range(200)]
    docs += [(200 + d, t + " more") for d, t in docs[:40]]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(4).localCheckpoint()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with counted(spark) as c:
            got = {r["doc_id"]: r["component_id"] for r in heavy_light.join(df, 3, heavy_light.Similarity(9, 10)).collect()}
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert got == {d: d - 200 if d >= 200 else d for d, _ in docs}
    assert c.shuffled_bytes < sum(len(t) for _, t in docs) / 4, c.shuffled_bytes


def test_intersections_in_parts():
    rng = np.random.default_rng(1)
    left, right = ([rng.choice(60, n, replace=False).astype(np.int64) for n in rng.integers(1, 30, 9)] for _ in range(2))
    assert heavy_light.intersections(left, right, 8).tolist() == [[len(set(a) & set(b)) for b in right] for a in left]


def test_jaccard_join_odd_rows(odd):
    got = {r["doc_id"]: r["component_id"] for r in heavy_light.join(odd).collect()}
    assert got == {d: 1 if d == 5 else d for d, _ in ODD}
    assert heavy_light.join(odd.limit(0)).count() == 0


def test_jaccard_join_of_an_id_with_several_texts(spark):
    linked, alone = " ".join(f"a{k}" for k in range(40)), " ".join(f"b{k}" for k in range(90))
    docs = [(1, linked), (1, alone), (2, linked + " more"), (3, " ".join(f"c{k}" for k in range(30)))]
    found = heavy_light.join(spark.createDataFrame(docs, "doc_id long, text string"), 3, heavy_light.Similarity(9, 10))
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in found.collect()) == [(1, 38, 1), (1, 88, 1), (2, 39, 1), (3, 28, 3)]


def test_jaccard_join_of_null_and_repeated_ids(spark):
    import corpus_pipeline as P

    text = lambda w, n=40: " ".join(f"{w}{k}" for k in range(n))
    # a and b: copy groups with a null id each; c and d: texts of one id and one number of shingles; e and f: alone, under null; g: one id, one text, twice
    docs = [(None, text("a")), (4, text("a") + " more"), (None, text("b")), (3, text("b") + " more"), (9, text("c")), (9, text("d")), (10, text("c")), (11, text("d") + " more")]
    docs += [(None, text("e")), (None, text("f")), (12, text("g")), (12, text("g")), (None, ""), (None, "")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = sorted((r["component_id"] or 0, r["doc_id"] or 0) for r in heavy_light.join(df, 5, heavy_light.Similarity(4, 5)).collect())
    assert got == sorted([(4, 0), (4, 4), (3, 0), (3, 3), (9, 9), (9, 9), (9, 10), (9, 11), (0, 0), (0, 0), (12, 12), (12, 12), (0, 0), (0, 0)])
    left = sorted((r["doc_id"] or 0, r["text"]) for r in P.near_duplicate_stage(spark, df, SF).collect())
    assert left == sorted([(4, text("a") + " more"), (3, text("b") + " more"), (9, text("c")), (9, text("d")), (0, text("e")), (0, text("f")), (12, text("g")), (0, ""), (0, "")])


def test_boundary_follows_cost():
    s = heavy_light.Similarity(9, 10)
    assert heavy_light.choose_boundary({}, s) == 0
    assert 0 < heavy_light.choose_boundary({8: 1000, 9: 1000}, s) <= heavy_light.MOST_LIGHT
    assert heavy_light.choose_boundary({40: 1000}, s) < 40


def test_bit_packing_round_trip():
    rng = np.random.default_rng(0)
    for bits in (1, 3, 8, 15, 16, 17, 20, 31, 32):
        for n in (0, 1, 63, 64, 65, 5000):
            ids = rng.integers(0, 1 << bits, n, dtype=np.uint64).astype(np.uint32)
            assert (token_files.unpack(token_files.pack(ids, bits), n, bits) == ids).all()
            image = token_files.Image(token_files.write_image([1, 2], [n // 2, n - n // 2], ids, bits))
            assert (image.ids(n // 3, n) == ids[n // 3 :]).all()
    assert token_files.width(50257) == 16 and token_files.width(32000) == 15


def test_token_files_against_the_library(spark, odd):
    from tokenizers import Tokenizer

    path = tokens.model_path("byte_bpe_50k.json")
    library = Tokenizer.from_file(path)
    images = token_files.write(odd, path)
    got = {r["doc_id"]: r for r in rows(token_files.read(images))}
    at, everything = 0, []
    for d, t in sorted(ODD, key=lambda x: (x[0] is not None, x[0] or 0)):
        ids = library.encode(t or "", add_special_tokens=False).ids + [0]
        assert (got[d]["start"], got[d]["n_tokens"], got[d]["ids_crc32"]) == (at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())), d
        at += len(ids)
        everything += ids
    assert token_files.slice_ids(images, 5, 40).tolist() == everything[5:40]
    assert token_files.read(token_files.write(odd.limit(0), path)).count() == 0


def test_packing_against_the_library(spark, odd):
    from tokenizers import Tokenizer

    path = tokens.model_path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    docs = odd.unionByName(Q.documents(spark, SF).withColumn("n", F.lit(1)).withColumn("doc_id", F.col("doc_id") + 1000))
    got = rows(packing.pack(docs, path))
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    total, seqs = 0, {}
    for r in got:
        ids = library.encode(texts[r["doc_id"]] or "", add_special_tokens=False).ids + [0]
        part = ids[r["start"] : r["start"] + r["length"]]
        assert r["start"] == 2048 * r["piece"] and len(part) == r["length"] == min(2048, len(ids) - r["start"])
        assert r["ids_crc32"] == zlib.crc32(np.array(part, "<u4").tobytes())
        total += len(part)
        seqs.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in seqs.values():
        spans.sort()
        assert spans[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:])) and sum(n for _, n in spans) <= 2048
    assert len(seqs) <= 1.05 * -(-total // 2048) + 1
    assert packing.pack(odd.limit(0), path).count() == 0


def test_packing_up_the_tree(spark, monkeypatch):
    monkeypatch.setattr(packing, "FAN_IN", 2)
    docs = spark.range(0, 64, 1, 8).select(F.col("id").alias("doc_id"), F.expr("repeat('a b c ', 100 + cast(id * 13 % 90 as int))").alias("text"))
    got = rows(packing.pack(docs, tokens.model_path("word_bpe_49k.json")))
    # besides the least number, one sequence of each of the 8 tasks may stay that fits with no other
    assert len(got) == 64 and len({r["sequence_id"] for r in got}) <= -(-sum(r["length"] for r in got) // 2048) + 8


def test_sentencepiece_equals_the_library(odd):
    import sentencepiece

    path = tokens.model_path("piece_bpe_32k.model")
    library = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = [t or "" for _, t in ODD] + ["  a\n b\tc  日本 ", "é́ 😀😀", "<s> </s> <0x0A>", "    "]
    own = pieces.Pieces(path)
    for t, ids in zip(texts, own.encode(texts)):
        ids = np.frombuffer(ids, "<u4")
        assert ids.tolist() == library.encode(t), t[:40]
        assert own.decode(ids) == t == library.decode(ids.tolist())
    encoded = pieces.encode(odd, path)
    assert all(r["decoded"] == (dict(ODD)[r["doc_id"]] or "") for r in pieces.decode(encoded, path).collect())


def test_unigram_search_by_brute_force(tmp_path):
    """The same pieces with the model's kind set to unigram: the largest sum of scores over all ways to cut a word."""
    with open(tokens.model_path("piece_bpe_32k.model"), "rb") as f:
        data = bytearray(f.read())
    data[data.index(b"\x18\x02", data.rindex(b"\x12") - 400) + 1] = pieces.UNIGRAM
    path = tmp_path / "unigram.model"
    path.write_bytes(bytes(data))
    own = pieces.Pieces(str(path))
    assert own.kind == pieces.UNIGRAM

    def best(word):
        ways = [(own.scores[own.id[word]], 1)] if word in own.id else [(float(own.unknown_score), 1)] if len(word) == 1 else []
        ways += [(best(word[:k])[0] + own.scores[own.id[word[k:]]], 0) for k in range(1, len(word)) if word[k:] in own.id]
        return max(ways)

    for word in ("▁the", "▁mat.", "▁internal", "▁facade", "▁unbel", "▁a1b2c3"):
        for found in (own.search([word])[0], own.search([word, word + "xyz"])[0]):
            assert sum(own.scores[k] for k in found) == best(word)[0]


def test_language_held_out(spark):
    got = rows(Q.op4_language(spark, SF))
    truth = {r["doc_id"]: r["lang"] for r in Q.documents(spark, SF).collect()}
    mine = [r["lang_pred"] == truth[r["doc_id"]] for r in got if r["held_out"]]
    assert len(mine) > 20 and np.mean(mine) > 0.95
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in got)


def test_emoji_are_no_letters():
    from allpairs.llm.ngrams import Grams

    assert Grams(["😀 🎉😀", "😀 a", "𐐀𠀀", "", None], 3).has_letter.tolist() == [False, True, True, False, False]


def test_language_of_emoji_is_unknown(spark):
    model = language.fit(spark.createDataFrame([(1, "the cat sat", "en"), (2, "die Katze sitzt", "de")], "doc_id long, text string, lang string"))
    got = language.predict(spark.createDataFrame([(1, "😀🎉 😀")], "doc_id long, text string"), model).first()
    assert got["lang_pred"] == language.UNKNOWN


def test_language_odd_rows(odd):
    empty = language.fit(odd.limit(0))
    assert {r["lang_pred"] for r in language.predict(odd, empty).collect()} == {"und"}
    got = {r["doc_id"]: (r["lang_pred"], r["lang_score"]) for r in language.predict(odd, language.fit(odd)).collect()}
    assert got[2] == got[3] == got[4] == ("und", 0.0) and got[1][0] == "en"


def test_language_scores_by_brute_force(spark):
    docs = Q.documents(spark, SF).limit(40).select("doc_id", "text", "lang")
    model = language.fit(docs)
    from allpairs.llm.ngrams import Grams

    for r in language.predict(docs, model).collect():
        g = Grams([r["text"]], max(language.ORDERS))
        total = sum(model.log_p[(k << language.BITS) + b] for k, n in enumerate(language.ORDERS) for b in g.buckets(n, language.BITS).tolist())
        assert model.languages[int(np.argmax(total))] == r["lang_pred"]


def test_toxicity(spark, odd):
    labels = spark.createDataFrame([(k, 1 if k % 2 else 0) for k in range(400)], "doc_id long, toxic int")
    docs = labels.select("doc_id", F.when(F.col("toxic") == 1, F.concat(F.lit("you idiot number "), F.col("doc_id") * 7919)).otherwise(F.concat(F.lit("a kind reply number "), F.col("doc_id") * 7919)).alias("text"))
    model = toxicity.fit(toxicity.training_rows(docs, labels))
    got = {r["doc_id"]: r["toxicity"] for r in toxicity.score(docs, model).collect()}
    assert all((got[k] >= toxicity.THRESHOLD) == bool(k % 2) for k in range(400) if zlib.crc32(str(k).encode()) % 3 == 1)
    scores = {r["doc_id"]: r["toxicity"] for r in toxicity.score(odd, model).collect()}
    assert scores[2] == scores[3] and all(0 <= x <= 1 for x in scores.values())
    none = toxicity.fit(toxicity.training_rows(docs, labels.limit(0)))
    assert max(r["toxicity"] for r in toxicity.score(docs, none).collect()) < 0.01


def scalar_coefficients(image):
    """One bit at a time, as the format is defined."""
    def codes(table):
        out, code, at = {}, 0, 16
        for n in range(1, 17):
            for s in table[at : at + table[n - 1]]:
                out[n, code] = s
                code += 1
            at += table[n - 1]
            code <<= 1
        return out

    units, blocks = int(np.prod(image.units)), []
    step = image.interval or units
    for n, scan in enumerate(image.scans):
        bits, at, dc = "".join(f"{b:08b}" for b in scan), 0, [0] * len(image.parts)

        def take(k):
            nonlocal at
            at += k
            return int(bits[at - k : at] or "0", 2)

        def symbol(table):
            code = 0
            for n in range(1, 17):
                code = code << 1 | take(1)
                if (n, code) in table:
                    return table[n, code]
            raise ValueError

        def value(size):
            v = take(size)
            return v if not size or v >> (size - 1) else v - (1 << size) + 1

        for _ in range(min(step, units - n * step)):
            for c, p in enumerate(image.parts):
                for _ in range(p[1] * p[2] if len(image.parts) > 1 else 1):
                    block = [0] * 64
                    dc[c] += value(symbol(codes(image.huffman[p[4]])))
                    block[0], k = dc[c], 1
                    while k < 64:
                        s = symbol(codes(image.huffman[16 + p[5]]))
                        if s == 0:
                            break
                        k += s >> 4
                        if s & 15:
                            block[k] = value(s & 15)
                        k += 1
                    blocks.append(block)
    return np.array(blocks)


def test_jpeg_round_trip_and_scalar_decoder(odd):
    payloads = [media.payload_of(x) for x in (b"", b"hello", bytes(range(256)) * 4, b"z" * 20000)]
    files = media.write_jpegs(payloads)
    images = [media.parse(f) for f in files]
    for p, image, coefs in zip(payloads, images, media.decode_scans(images)):
        assert media.payload_from(image, coefs) == p
        if len(p) < 5000:
            assert (coefs.reshape(-1, 64) == scalar_coefficients(image)).all()
    got = rows(media.features(media.store(odd)))
    texts = dict(ODD)
    for r in got:
        p = media.payload_of((texts[r["doc_id"]] or "").encode())
        assert r["payload_sha256"] == hashlib.sha256(p).hexdigest() and r["tail_crc32"] == zlib.crc32(p[-16:]) and r["payload_bytes"] == len(p)
    assert media.features(media.store(odd.limit(0))).count() == 0


def test_jpeg_with_runs_subsampling_and_no_restarts():
    """A file built bit by bit: 4:2:0, runs of zeros, end of block, one interval."""
    codes = {(0, s): (s, 4) for s in range(12)}
    ac = {s: (k, 8) for k, s in enumerate([0, 0xF0, 0x01, 0x11, 0x23, 0x52, 0x0A])}
    rng = random.Random(1)
    bits = ""

    def put(code, n):
        nonlocal bits
        bits += f"{code:0{n}b}"

    want = []
    before = [0, 0, 0]
    for _ in range(4):
        for c, times in ((0, 4), (1, 1), (2, 1)):
            for _ in range(times):
                block = [0] * 64
                block[0] = rng.randint(-900, 900)
                diff = block[0] - before[c]
                before[c] = block[0]
                size = abs(diff).bit_length()
                put(*codes[0, size])
                if size:
                    put(diff if diff > 0 else diff + (1 << size) - 1, size)
                k = 1
                for s in (0x01, 0x11, 0xF0, 0x23, 0x52, 0x0A):
                    put(*ac[s])
                    k += s >> 4
                    if s & 15:
                        v = rng.choice([-1, 1]) * rng.randint(1 << ((s & 15) - 1), (1 << (s & 15)) - 1)
                        put(v if v > 0 else v + (1 << (s & 15)) - 1, s & 15)
                        block[k] = v
                    k += 1
                put(*ac[0])
                want.append(block)
    bits += "1" * (-len(bits) % 8)
    body = int(bits, 2).to_bytes(len(bits) // 8, "big").replace(b"\xff", b"\xff\0")
    seg = media._segment
    dc_table = b"\0" + bytes([0, 0, 0, 12] + [0] * 12) + bytes(range(12))
    ac_table = b"\x10" + bytes([0] * 7 + [7] + [0] * 8) + bytes(ac)
    data = b"\xff\xd8" + seg(0xDB, b"\0" + b"\2" * 64) + seg(0xC4, dc_table + ac_table) + seg(0xC0, bytes([8, 0, 32, 0, 32, 3, 1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])) + seg(0xDA, b"\3\1\0\2\0\3\0\0\x3f\0") + body + b"\xff\xd9"
    image = media.parse(data)
    coefs = media.decode_scans([image])[0]
    assert (coefs.reshape(-1, 64) == np.array(want)).all() and (scalar_coefficients(image) == np.array(want)).all()
    assert media.thumbnail(image, coefs).shape == (4, 4)


def test_pipeline(spark):
    import corpus_pipeline as P

    docs = Q.documents(spark, SF)
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns, name
        before, after = rows(docs), rows(out)
        if name == "near_duplicates":
            want = brute_components([(r["doc_id"], r["text"]) for r in before], 5, 4, 5)
            assert {r["doc_id"] for r in after} == {d for d, (_, c) in want.items() if c == d}
        elif name == "personal_data":
            assert len(after) == len(before) and not any(base_spans(r["text"]) for r in after)
        else:
            assert 0.8 * len(before) <= len(after) <= len(before)
        docs = spark.createDataFrame(after, docs.schema)
    assert {"doc_id", "sequence_id", "offset"} <= set(P.packing_stage(spark, docs, SF).columns)
