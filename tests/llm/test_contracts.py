"""What the contracts say of odd inputs, and plain versions of what is learned or searched."""

import math
import random
import time
import unicodedata
import re
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

pytest.importorskip("allpairs.llm")
from allpairs.llm import common, fingerprints, heavy_light, language, packing, personal_data, pieces, token_files, tokens, toxicity  # noqa: E402
from allpairs.llm import queries as Q  # noqa: E402
from test_operators import ODD, brute_components, near_copies, rows  # noqa: E402

SF = "/root/testdata/sf0.001"
MARKED = ["a <|endoftext|> b", "<|endoftext|>", "x<|endoftext|><|startoftext|>y  z", "<|ENDOFTEXT|> q", "< |endoftext|>", "plain  text\n", "<|startoftext|> Straße ﬁn"]


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_added_tokens_in_a_text_get_the_library_s_ids(name):
    from tokenizers import Tokenizer

    path = tokens.model_path(name)
    library, own = Tokenizer.from_file(path), tokens.Encoder(path)
    for _ in range(2):
        got = [np.frombuffer(x, "<u4").tolist() for x in own.encode(MARKED)]
        assert got == [library.encode(t, add_special_tokens=False).ids for t in MARKED]
    assert any(library.token_to_id("<|endoftext|>") in x for x in got)


def test_edited_fingerprints_are_compared_by_bytes(spark):
    def canon(t):
        return " ".join(re.split(r"[\s\x1c-\x1f\x85]+", unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t).casefold()))).strip()

    texts = [f"text number {k * 7919 % 200} {'x' * (k % 5)}" for k in range(200)] + ["same text here", "same text here", "Same  TEXT here", "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in rows(fingerprints.fingerprints(docs, wide=lambda c: F.substring(fingerprints.digest(c), 1, 1)))}
    own = {}
    for k, t in enumerate(texts):
        t, after = t or "", texts[(k + 1) % len(texts)] or ""
        edited = t[: len(t) - len(t) // 4] + after[: len(t) // 4]
        assert (got[k]["fp"] == got[k]["edited_fp"]) == (canon(t) == canon(edited)), k
        assert own.setdefault(canon(t), got[k]["fp"]) == got[k]["fp"]
    assert len(set(own.values())) == len(own)


def test_ranges_are_cut_twice(spark, monkeypatch):
    monkeypatch.setattr(fingerprints, "BUCKET_ROWS", 3)
    monkeypatch.setattr(fingerprints, "MOST_CUTS", 5)
    docs = spark.range(200).select((F.col("id") * F.col("id") - 50).alias("doc_id"), F.concat(F.lit("t"), F.col("id")).alias("text"))
    assert fingerprints._placed(docs).select("_bucket").distinct().count() > 20
    assert {r["text"]: r["next_text"] for r in fingerprints.with_next(docs).collect()} == {f"t{k}": f"t{(k + 1) % 200}" for k in range(200)}


def ordinary_unigram(tmp_path):
    """The given pieces as a unigram model whose scores are of the size that such models have."""
    with open(tokens.model_path("piece_bpe_32k.model"), "rb") as f:
        data = bytearray(f.read())
    data[data.index(b"\x18\x02", data.rindex(b"\x12") - 400) + 1] = pieces.UNIGRAM

    def varint(at):
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out, at

    at = 0
    while data[at] == 0x0A:
        size, at = varint(at + 1)
        p, at = at, at + size
        while p < at:
            key, p = varint(p)
            if key & 7 == 2:
                n, p = varint(p)
                p += n
            elif key & 7 == 5:
                (score,) = struct.unpack_from("<f", data, p)
                if score < 0:
                    struct.pack_into("<f", data, p, -3 - math.log1p(min(-score, 40000.0)))
                p += 4
            else:
                _, p = varint(p)
    path = tmp_path / "ordinary.model"
    path.write_bytes(bytes(data))
    return str(path)


def test_unigram_search_equals_the_library(spark, tmp_path):
    """Every word has the library's pieces; in whole texts the library adds sums in single precision, so of equal sums it may take another."""
    import sentencepiece

    path = ordinary_unigram(tmp_path)
    own, library = pieces.Pieces(path), sentencepiece.SentencePieceProcessor(model_file=path)
    texts = [r["text"] for r in Q.documents(spark, SF).collect() if r["text"]]
    words = sorted({w for t in texts for w in t.split()}) + ["x" * 300, "ab1" * 400]
    for w, ids in zip(words, own.encode(words), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(w), w
    same = 0
    for t, ids in zip(texts, own.encode(texts), strict=True):
        mine, theirs = np.frombuffer(ids, "<u4").tolist(), library.encode(t)
        assert own.decode(np.array(mine, np.uint32)) == own.decode(np.array(theirs, np.uint32)) == t
        assert abs(sum(own.scores[k] for k in mine) - sum(own.scores[k] for k in theirs)) < 1e-3 * len(mine)
        same += mine == theirs
    assert same > 0.9 * len(texts)


def test_pairs_of_pieces_stop_at_their_border():
    """Pairs are tested without merging on after a merge across their border, with the result of whole merging; all kinds of ids are decoded."""
    path = tokens.model_path("piece_bpe_32k.model")
    own = pieces.Pieces(path)
    rng = random.Random(5)

    def plain(text):
        parts = list(text)
        while found := [(-own.scores[own.id[p + q]], k) for k, (p, q) in enumerate(zip(parts, parts[1:])) if p + q in own.id]:
            k = min(found)[1]
            parts[k : k + 2] = [parts[k] + parts[k + 1]]
        return [own.id.get(p, own.none) for p in parts]

    ids = list(own.id.values())
    for a, b in [(rng.choice(ids), rng.choice(ids)) for _ in range(500)] + [(own.id["t"], own.id["h"])]:
        text = own.text[a] + own.text[b]
        whole = plain(text)
        assert own.merge(text) == whole
        assert own.merge(text, len(own.text[a])) in (whole, [])
        assert own._pair(a * (own.none + 1) + b) == (whole == [a, b])
    assert own.merge("th", 1) == []
    text = "日本 x 𝄞\u0001 end"
    assert own.decode(np.frombuffer(own.encode([text])[0], "<u4")) == text
    assert own.decode(np.array([min(own.control), own.id["t"], own.unknown, own.id["h"]])) == "t ⁇ h"


def test_words_of_any_length_advance_together():
    import sentencepiece

    path = tokens.model_path("piece_bpe_32k.model")
    own, library = pieces.Pieces(path), sentencepiece.SentencePieceProcessor(model_file=path)
    rng = random.Random(2)
    words = ["".join(rng.choice("abcdeélt0123日") for _ in range(rng.randint(1, 400))) for _ in range(60)]
    assert [np.frombuffer(x, "<u4").tolist() for x in own.encode(words)] == [library.encode(w) for w in words]


def test_rounds_of_packing_lose_nothing(spark, monkeypatch):
    monkeypatch.setattr(packing, "NODE_ITEMS", 8)
    docs = spark.range(0, 90, 1, 6).select(F.col("id").alias("doc_id"), F.expr("repeat('a b c ', 350 + cast(id * 13 % 90 as int))").alias("text"))
    got = rows(packing.pack(docs, tokens.model_path("word_bpe_49k.json")))
    assert len(got) == 90 and len({r["sequence_id"] for r in got}) == 90  # no two fit into one
    small = docs.select("doc_id", F.expr("repeat('a b c ', 20 + cast(doc_id as int))").alias("text"))
    got = rows(packing.pack(small, tokens.model_path("word_bpe_49k.json")))
    places = {}
    for r in got:
        places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for spans in places.values():
        spans.sort()
        assert spans[0][0] == 0 and all(a + n == b for (a, n), (b, _) in zip(spans, spans[1:])) and sum(n for _, n in spans) <= 2048
    assert len(got) == 90 and len(places) <= -(-sum(r["length"] for r in got) // 2048) + 3


def test_slices_of_token_files_reach_over_images(spark, monkeypatch):
    monkeypatch.setattr(token_files, "IMAGE_IDS", 40)
    docs = spark.range(60).select(F.col("id").alias("doc_id"), F.concat(F.lit("some words and the number "), F.col("id")).alias("text"))
    images = token_files.write(docs, tokens.model_path("byte_bpe_50k.json"))
    everything = token_files.slice_ids(images, 0, 1 << 40)
    assert images.count() > 5 and len(everything) == images.agg(F.sum("n_ids")).first()[0]
    assert token_files.slice_ids(images, 33, 210).tolist() == everything[33:210].tolist() and len(token_files.slice_ids(images, 9, 9)) == 0


@pytest.mark.parametrize("k,num,den", [(3, 9, 10), (5, 4, 5)])
def test_jaccard_join_with_all_keys_hot(spark, monkeypatch, k, num, den):
    monkeypatch.setattr(common, "HOT_ROWS", 2)
    monkeypatch.setattr(heavy_light, "LIST_BLOCK", 3)
    if k == 5:  # components alone verify no pairs inside
        monkeypatch.setattr(heavy_light, "_links_inside", None)
    docs = near_copies(k, 130, 40)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in heavy_light.join(df, k, heavy_light.Similarity(num, den), links=k == 3).collect()}
    assert got == brute_components(docs, k, num, den)


def test_statement_of_the_jaccard_join(spark):
    import duckdb

    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    want = c.execute(Q.oracle_sql()["op1_ngram_jaccard_join"]).fetchdf()
    got = Q.op1_ngram_jaccard_join(spark, SF).toPandas()
    assert sorted(map(tuple, got[want.columns].values.tolist())) == sorted(map(tuple, want.values.tolist()))


# --- personal data


def test_reliabilities_are_found_again():
    rng = np.random.default_rng(4)
    n, real = 40_000, 0.3
    # chances of a vote for and against, on real spans and on others
    chances = [((0.8, 0.05), (0.1, 0.6)), ((0.5, 0.1), (0.15, 0.5)), ((0.6, 0.0), (0.05, 0.1)), ((0.3, 0.02), (0.02, 0.4)), ((0.2, 0.15), (0.1, 0.25))]
    y = rng.random(n) < real
    votes = np.zeros((n, len(chances)))
    for k, (on_real, on_others) in enumerate(chances):
        u = rng.random(n)
        up, down = np.where(y, on_real[0], on_others[0]), np.where(y, on_real[1], on_others[1])
        votes[:, k] = np.where(u < up, 1, np.where(u < up + down, -1, 0))
    patterns, back, counts = np.unique(votes, axis=0, return_inverse=True, return_counts=True)
    p, reliability, prior = personal_data.expectation_maximisation(patterns, counts.astype(float))
    for k in range(len(chances)):
        cast = votes[:, k] != 0
        assert abs(reliability[k] - ((votes[cast, k] > 0) == y[cast]).mean()) < 0.05
    assert abs(prior - real) < 0.05 and ((p[back.reshape(-1)] >= 0.5) == y).mean() > 0.85


def spans_with_answers(rng, n):
    """Texts with one proposal each, and whether it is personal."""
    pick = rng.choice
    letters = lambda k, a="abcdefghijkmnpqrstuvwxyzABCDEFGHJKLMNPQRSTUVWXYZ0123456789": "".join(pick(a) for _ in range(k))
    digits = lambda k: "".join(pick("0123456789") for _ in range(k))
    out = []
    for _ in range(n):
        real, kind = rng.random() < 0.5, pick(["secret", "contact"])
        if kind == "secret" and real:
            value = letters(rng.randint(18, 40))
            text = pick([f"the password = {value} is set", f"use api_key: '{value}' here", f"login with key {value} now", f"bearer {value} expires soon", f"access_token={value}", f"config auth {value} rotate it", f"x_setting = {value} do not share"])
        elif kind == "secret":
            value = letters(rng.randint(18, 40), "abcdef0123456789") if rng.random() < 0.5 else pick(["model", "release", "filename", "chapter", "paragraph"]) + digits(2) + pick(["information", "documentation", "configuration", "measurement"])
            text = pick([f"commit {value} was merged", f"sha256: {value} checked", f"the file {value} png", f"uuid = {value}", f"see {value} for more", f"build {value} digest ok", f"version={value}"])
        elif real:
            a, b, c = f"{rng.randint(2, 9)}{rng.randint(0, 9)}{rng.randint(2, 9)}", f"{rng.randint(2, 9)}{rng.randint(2, 9)}{rng.randint(0, 9)}", digits(4)
            text = pick([f"call {a}-{b}-{c} today", f"phone: ({a}) {b}-{c}", f"ring me at {a}.{b}.{c} anytime", f"mobile {a} {b} {c}", f"we are at ({a}) {b}-{c} ext 4", f"fax {a}{b}{c}"])
        else:
            text = pick([f"order {digits(8)} shipped", f"on {rng.randint(1990, 2029)}-0{rng.randint(1, 9)}-{rng.randint(10, 28)} it rained", f"invoice {digits(5)}-{digits(4)} paid", f"total {digits(4)} {digits(4)} units", f"from {rng.randint(1900, 1999)}-{rng.randint(2000, 2029)} only", f"about {digits(7)} people", f"page {digits(3)}-{digits(4)}", f"serial 1{digits(9)}"])
        out.append((text, kind, real))
    return out


def test_the_classifier_beats_every_labeler(spark):
    made = spans_with_answers(random.Random(8), 3000)
    docs = spark.createDataFrame([(k, t) for k, (t, _, _) in enumerate(made)], "doc_id long, text string")
    _, model = personal_data.find(docs)
    found = personal_data.propose(docs).select("doc_id", F.explode("spans").alias("s")).select("doc_id", "s.*", model.score(F.col("s")).alias("score")).collect()
    for kind in personal_data.MORE:
        mine = [r for r in found if r["kind"] == kind and made[r["doc_id"]][1] == kind]
        truth = np.array([made[r["doc_id"]][2] for r in mine])
        right = ((np.array([r["score"] for r in mine]) >= 0.5) == truth).mean()
        alone = {v: ((np.array([r[v] for r in mine]) > 0) == truth).mean() for v in personal_data.VOTES}
        assert len(mine) > 1000 and right > 0.9 and right > max(alone.values()), (kind, right, alone)
        kept = np.array([r["score"] for r in mine]) >= 0.5
        assert 0.3 < kept.mean() < 0.7  # it keeps some and rejects others


def test_many_spans_take_time_in_proportion(spark):
    def seconds(n):
        docs = spark.createDataFrame([(1, "mail some.one@example.com now " * n)], "doc_id long, text string")
        began = time.perf_counter()
        found, _ = personal_data.find(docs, carry=("doc_id", "text"))
        got = found.select(F.size("spans").alias("n"), personal_data.redact(F.col("text"), F.col("spans")).alias("t")).first()
        assert got["n"] == n and got["t"] == "mail <EMAIL> now " * n
        return time.perf_counter() - began

    seconds(100)
    small, large = seconds(3_000), seconds(24_000)
    assert large < 12 * small + 5


def test_redaction_joins_overlaps_and_keeps_all_else(spark):
    rng = random.Random(6)
    cases = []
    for n in (0, 1, 5, 2047, 2048, 2049, 6000):
        text = "".join(rng.choice("ab😀é ") for _ in range(n))
        spans = []
        for _ in range(rng.randint(0, 12) if n else 0):
            a = rng.randrange(n)
            spans.append((rng.choice(["email", "ip"]), a, min(n, a + rng.randint(1, 900))))
        cases.append((text, spans))

    def plain(text, spans):
        out, at, regions = [], 0, []
        for kind, a, b in sorted(spans, key=lambda s: (s[1], -s[2], s[0])):
            if regions and a < regions[-1][2]:
                regions[-1][2] = max(regions[-1][2], b)
            else:
                regions.append([kind, a, b])
        for kind, a, b in regions:
            out.append(text[at:a] + f"<{kind.upper()}>")
            at = b
        return "".join(out) + text[at:]

    df = spark.createDataFrame(cases, "text string, spans array<struct<kind:string,start:int,end:int>>")
    assert [r["t"] for r in df.select(personal_data.redact(F.col("text"), F.col("spans")).alias("t")).collect()] == [plain(*c) for c in cases]


# --- learned models against plain versions


def plain_grams(text, n):
    s = " " + " ".join("".join(c if c.isalpha() else " " for c in text.lower()).split()) + " "
    return [s[k : k + n] for k in range(len(s))] if s.strip() else []


def test_language_by_a_plain_classifier(spark):
    docs = [(r["doc_id"], r["text"], r["lang"]) for r in Q.documents(spark, SF).collect()]
    learn = [d for d in docs if zlib.crc32(str(d[0]).encode()) % 4 != 2 and d[1] and d[2]]
    langs = sorted({d[2] for d in learn})
    counts = {(x, n): Counter() for x in langs for n in language.ORDERS}
    for _, t, x in learn:
        for n in language.ORDERS:
            counts[x, n].update(plain_grams(t, n))
    size = 1 << language.BITS

    def guess(t):
        score = {x: sum(math.log((counts[x, n][g] + 0.5) / (sum(counts[x, n].values()) + 0.5 * size)) for n in language.ORDERS for g in plain_grams(t, n)) for x in langs}
        return max(langs, key=lambda x: score[x])

    got = {r["doc_id"]: r["lang_pred"] for r in Q.op4_language(spark, SF).collect()}
    some = [d for d in docs if d[1] and any(c.isalpha() for c in d[1]) and len(d[1]) < 4000][:80]
    same = [got[d] == guess(t) for d, t, _ in some]
    assert np.mean(same) >= 0.98


def test_language_ties_and_many_languages(spark):
    both = spark.createDataFrame([(1, "abc abc", "xx"), (2, "abc abc", "aa"), (3, None, "en"), (4, "zzz", None)], "doc_id long, text string, lang string")
    model = language.fit(both)
    assert model.languages == ["aa", "xx"]
    got = rows(language.predict(both.select("doc_id", "text", F.lit("mine").alias("lang_pred")), model, into=("_p", "_s")))
    assert {r["doc_id"]: (r["_p"], r["lang_pred"]) for r in got} == {1: ("aa", "mine"), 2: ("aa", "mine"), 3: ("und", "mine"), 4: ("aa", "mine")}
    assert language.predict(both.limit(0), model).count() == 0
    assert language.bits_for(4) == language.BITS and all(4 * 3 * n << language.bits_for(n) <= language.MOST_MODEL_BYTES for n in (341, 1000, 100_000))


def test_toxicity_by_a_plain_classifier(spark):
    """Log-count ratios of string n-grams, and a logistic regression by plain gradient steps on a dense matrix."""
    rng = random.Random(9)
    bad, good, both = ["idiot", "moron", "scum"], ["kind", "lovely", "thanks"], [f"w{chr(97 + k)}{chr(97 + k * 7 % 26)}" for k in range(26)]
    made = []
    for k in range(240):
        words = [rng.choice(both) for _ in range(12)]
        toxic = k % 3 == 0
        words[rng.randrange(12)] = rng.choice(bad if toxic else good)
        made.append((k, " ".join(words), int(toxic)))
    docs = spark.createDataFrame([m[:2] for m in made], "doc_id long, text string")
    labels = spark.createDataFrame([(k, t) for k, _, t in made], "doc_id long, toxic int")
    model = toxicity.fit(toxicity.training_rows(docs, labels))
    got = {r["doc_id"]: r["toxicity"] for r in toxicity.score(docs, model).collect()}

    learn = [m for m in made if zlib.crc32(str(m[0]).encode()) % 3 != 1]
    grams = lambda t: {(n, g) for n in toxicity.ORDERS for g in plain_grams(t, n)}
    y = np.array([m[2] for m in learn], float)
    texts, toxic = Counter(), Counter()
    for m in learn:
        texts.update(grams(m[1]))
        if m[2]:
            toxic.update(grams(m[1]))
    ratio = {g: math.log(((toxic[g] + 1) / (y.sum() + 2)) / ((texts[g] - toxic[g] + 1) / ((1 - y).sum() + 2))) for g in texts if texts[g] >= toxicity.LEAST_TEXTS}
    ratio = {g: r for g, r in ratio.items() if abs(r) >= toxicity.LEAST_RATIO}
    names = sorted(ratio)
    x = np.array([[ratio[g] if g in grams(m[1]) else 0.0 for g in names] for m in learn])
    each = np.where(y > 0, 0.5 / y.sum(), 0.5 / (1 - y).sum()) * len(y)
    w, b = np.zeros(len(names)), 0.0
    for _ in range(6000):
        e = each * (1 / (1 + np.exp(-(x @ w + b))) - y)
        w -= 0.002 * (x.T @ e + toxicity.RIDGE * w)
        b -= 0.002 * e.sum()
    for k, t, toxic_ in made:
        have = grams(t)
        want = 1 / (1 + math.exp(-(sum(w[i] * ratio[g] for i, g in enumerate(names) if g in have) + b)))
        assert abs(got[k] - want) < 0.05, (k, got[k], want)
        if zlib.crc32(str(k).encode()) % 3 == 1:
            assert (got[k] >= toxicity.THRESHOLD) == bool(toxic_)


def test_toxicity_with_repeated_and_contradicting_labels(spark):
    docs = spark.createDataFrame([(k, "bad awful word" if k % 2 else "good fine word") for k in range(60)] + [(None, "no id"), (3, "bad awful word")], "doc_id long, text string")
    labels = spark.createDataFrame([(k, k % 2) for k in range(60)] * 2 + [(0, 1), (1, 0), (None, 1), (7, None), (999, 1)], "doc_id long, toxic int")
    chosen = toxicity.training_rows(docs, labels)
    assert chosen.count() == chosen.select("doc_id").distinct().count() and chosen.filter("doc_id = 0").first()["toxic"] in (1, None)
    got = {r["doc_id"]: r["toxicity"] for r in toxicity.score(docs, toxicity.fit(chosen)).collect()}
    assert got[5] > 0.7 > got[4] and toxicity.score(docs.limit(0), toxicity.fit(chosen)).count() == 0


# --- the pipeline


CLASHING = ["row", "_row", "_id", "spans", "toxicity", "lang_pred", "lang_score", "worded", "size", "set_id", "n", "doc", "into", "a b.c"]


@pytest.fixture(scope="module")
def clashing(spark):
    texts = [r["text"] for r in Q.documents(spark, SF).orderBy("doc_id").collect()][:40]
    made = [(k, t, "en", "s", None) for k, t in enumerate(texts)] + [(d, t, None, None, 1) for d, t in ODD] + [(None, "three different texts", "en", "s", 1), (None, "with no id of their own", "en", "s", 1), (3, texts[3], "en", "other", 1)]
    df = spark.createDataFrame(made, "doc_id long, text string, lang string, source string, n_chars long")
    for c in CLASHING:
        df = df.withColumn(c, F.lit(f"mine {c}"))
    return df


@pytest.mark.parametrize("name", ["toxicity", "language", "near_duplicates", "personal_data", "packing"])
def test_stages_keep_foreign_columns_and_take_empty_tables(spark, clashing, name):
    import corpus_pipeline as P

    stage = dict(P.STAGES)[name]
    out = stage(spark, clashing, SF)
    if name != "packing":
        assert out.columns == clashing.columns and out.dtypes == clashing.dtypes
        got = rows(out)
        assert got and all(r[c] == f"mine {c}" for r in got for c in CLASHING)
        before, after = Counter((r["doc_id"], r["text"]) for r in rows(clashing)), Counter((r["doc_id"], r["text"]) for r in got)
        if name in ("toxicity", "language"):
            assert not after - before and after[3, clashing.filter("doc_id = 3 and source = 'other'").first()["text"]] in (0, 2)
        if name == "language":
            assert not any(t is None or not any(c.isalpha() for c in t) for _, t in after) and after[None, "with no id of their own"] == 1
        if name == "near_duplicates":
            assert after[None, "three different texts"] == after[None, "with no id of their own"] == after[None, "a row without id"] == 1
        if name == "personal_data":
            assert len(got) == sum(before.values()) and all(r["n_chars"] == len(r["text"]) for r in got)
    else:
        assert sum(r["piece"] == 0 for r in rows(out)) == clashing.count()
    assert stage(spark, clashing.limit(0), SF).count() == 0


def test_filtering_stages_decide_as_their_operators_do(spark):
    import corpus_pipeline as P

    docs = Q.documents(spark, SF)
    toxic = {r["doc_id"] for r in Q.op7_toxicity(spark, SF).collect() if r["predicted"] == 1}
    assert {r["doc_id"] for r in P.toxicity_stage(spark, docs, SF).collect()} == {r["doc_id"] for r in docs.collect()} - toxic
    known = {r["doc_id"] for r in Q.op4_language(spark, SF).collect() if r["lang_pred"] != "und" and r["score"] >= P.LEAST_LANGUAGE_SCORE}
    assert {r["doc_id"] for r in P.language_stage(spark, docs, SF).collect()} == known
