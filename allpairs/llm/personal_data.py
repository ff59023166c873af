"""Personal data in texts by weak supervision, in DataFrame functions only.

Patterns propose spans, among them many that are none: any value given to a name, any long token of
letters and digits, any run of numbers that could be dialled.  Five labelers vote on each proposal, for,
against or not at all: its shape, a check of its parts, gazetteers (top-level domains, calling codes,
issuer ranges, names that credentials are given to), the words before it and the words after it.  What is
counted of vote patterns goes through expectation-maximisation, which estimates how often each labeler
votes which way on real spans and on others, and how many are real; a logistic span classifier learns the
resulting probabilities from votes and features of the span, and decides.  Spans of the base patterns always
stay; the classifier decides on the other proposals (credentials, and phone numbers without a country sign).

Only counts of (kind, votes, features) leave the executors: a bounded table whatever the input.  Positions are
code points, ends exclusive; they come from running sums, so a text costs its length times the logarithm of
its number of spans.

Nulls: null text is the empty text, without spans.  Empty tables give empty results.  Repeated rows are searched
each, texts of any length whole.  Spans of different kinds may overlap; redaction joins those into one.
Proposals with a score of just the threshold stay.  Input columns keep their names and values, except that
``propose`` and ``find`` replace one of the name they are given for the spans.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import quoted

# What each kind looks like.  Possessive repetition keeps Java's matcher linear and
# free of recursion; the matches are those of the plain patterns.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?=[0-9][\x20-]?[0-9])[0-9]++(?:[\x20-][0-9]++)*+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
MORE = {
    "secret": r"(?<![A-Za-z0-9_])(?:(?:AKIA|ASIA|ghp_|gho_|xox[bp]-|sk_live_|AIza)[A-Za-z0-9_-]{12,}+|[A-Za-z_][A-Za-z0-9_-]{1,40}+\s{0,2}[=:]\s{0,2}[\x22']?[^\s\x22']{8,}+|(?<![./+-])(?=[A-Za-z_/+-]*+[0-9])(?=[0-9_/+-]*+[A-Za-z])[A-Za-z0-9_/+-]{16,}+)",
    "contact": r"(?<![0-9A-Za-z+.,/-])(?<![0-9] )(?<!\+[0-9]{1,3}[ .-]{1,2})(?<!\)[ -]?)(?:\([0-9]{2,4}\) ?|[0-9]{2,5}[ .-]?)[0-9]{2,4}(?:[ .-]?[0-9]{2,4})?+(?![ .,/-]?[0-9]|[A-Za-z])",
}
KINDS = (*BASE, *MORE)
#: A cheap test that a text can have the kind at all.
HINT = {"email": "@", "ip": ".", "card": None, "phone": "+", "secret": None, "contact": None}

# Gazetteers.
TOP_LEVEL = "com org net edu gov mil int io info biz dev app me tv co ai at au be br ca ch cn cz de dk es eu fi fr gr hu ie il in it jp kr lu mx nl no nz pl pt ro ru se sg sk tr ua uk us za".split()
CALLING_CODES = "1 7 20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98 212 213 216 351 352 353 354 356 357 358 359 370 371 372 380 385 386 420 421 852 886 962 966 971 972 974".split()
#: First and last beginnings of card numbers, six digits wide.
ISSUERS = ((400000, 499999), (510000, 559999), (222100, 272099), (340000, 349999), (370000, 379999), (601100, 601199), (640000, 659999), (352800, 358999), (300000, 305999), (360000, 369999), (620000, 629999))
CREDENTIAL_NAMES = "password passwd pwd pass passphrase secret token auth auth_token access_token refresh_token api_key apikey api-key access_key secret_key private_key client_secret credential credentials bearer session_key passwort kennwort contrasena clave mot_de_passe jeton".split()
OTHER_NAMES = "id uuid guid sha sha1 sha256 md5 crc checksum digest hash commit revision version build isbn issn doi url uri href src http https ftp file path class style width height size color name title date time page order invoice sku serial model ref email mail tel".split()
PREFIXES = "AKIA ASIA ghp_ gho_ xoxb- xoxp- sk_live_ AIza".split()
# Words near a span that speak for it, and against it.
BEFORE = {
    "email": ("mail contact write reach kontakt schreib correo courriel escribe", "example regex pattern sprintf git@"),
    "ip": ("ip host server addr address adresse node ping from", "version release section chapter v kapitel"),
    "card": ("card visa credit debit mastercard karte carte tarjeta pay", "isbn order serial invoice sku id tracking nummer"),
    "phone": ("phone call tel fax mobile cell reach anruf telefon appel llama", "score total sum plus"),
    "secret": ("key secret token password login credential credentials bearer auth authorization passwort clave", "sha sha1 sha256 md5 checksum digest commit uuid guid isbn file image example placeholder dummy hash version build revision"),
    "contact": ("phone call tel fax mobile cell reach dial anruf telefon telephone telefono appel llama ruf", "order invoice isbn issn serial version page figure fig table section id no nr sku ref total sum score tracking from in between year"),
}
AFTER = {
    "email": ("or and for anytime", "regex"),
    "ip": ("port host server", "release version build"),
    "card": ("exp expires cvv cvc valid", "units pieces items"),
    "phone": ("ext or fax mobile anytime", "points percent"),
    "secret": ("expires keep do not secret rotate", "checksum mismatch png jpg zip pdf html commit digest"),
    "contact": ("ext fax mobile anytime now today extension", "units pieces items pages eur usd dollars euros kg km percent times people years"),
}
VOTES = ("shape", "check", "gazetteer", "before", "after")
SHAPES = ("long", "digits", "mixed", "cased", "parted")
FEATURES = (*VOTES, *SHAPES)
AROUND = 24


def _let(value: Column, body) -> Column:
    """``body`` of a value that is made once, however often it is used there."""
    return F.transform(F.array(value), body)[0]


def running(values: Column, combine) -> Column:
    """Each value combined with all before it, by doubling steps: linear work a step, a logarithmic number of steps."""

    def step(acc: Column, k: Column) -> Column:
        shift = F.pow(F.lit(2), k).cast("int")
        earlier = F.concat(F.array_repeat(F.lit(None).cast("int"), shift), F.slice(acc, F.lit(1), F.greatest(F.size(acc) - shift, F.lit(0))))
        return F.zip_with(acc, earlier, lambda x, y: F.when(y.isNull(), x).otherwise(combine(x, y)))

    def doubled(v: Column) -> Column:
        return F.when(F.size(v) <= 1, v).otherwise(F.aggregate(F.sequence(F.lit(0), F.ceil(F.log2(F.size(v))).cast("int") - 1), v, step))

    return _let(values, doubled)


def _found(kind: str, text: Column) -> Column:
    """The kind's matches with their starts and a few characters before and after each, from what stands between them."""
    pattern = {**BASE, **MORE}[kind]

    def placed(v: Column) -> Column:
        n = F.size(v["hits"])
        ends = running(F.zip_with(F.slice(v["gaps"], F.lit(1), n), v["hits"], lambda g, h: F.length(g) + F.length(h)), lambda x, y: x + y)
        zipped = F.arrays_zip(v["hits"].alias("hit"), ends.alias("end"), F.slice(v["gaps"], F.lit(1), n).alias("lead"), F.slice(v["gaps"], F.lit(2), n).alias("trail"))
        return F.transform(zipped, lambda x: F.struct((x["end"] - F.length(x["hit"])).alias("start"), x["hit"].alias("hit"), F.lower(F.substring(x["lead"], -AROUND, AROUND)).alias("before"), F.lower(F.substring(x["trail"], 1, AROUND)).alias("after")))

    all_ = _let(F.struct(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hits"), F.split(text, pattern, -1).alias("gaps")), placed)
    can = F.contains(text, F.lit(HINT[kind])) if HINT[kind] else F.lit(True)
    return F.when(can & F.rlike(text, F.lit(pattern)), all_).otherwise(F.array().cast("array<struct<start:int,hit:string,before:string,after:string>>"))


def luhn(digits: Column) -> Column:
    n = F.length(digits)

    def step(acc: Column, k: Column) -> Column:
        d = F.substring(digits, n - k + 1, F.lit(1)).cast("int")
        twice = F.when(F.pmod(k, F.lit(2)) == 0, d * 2).otherwise(d)
        return acc + F.when(twice > 9, twice - 9).otherwise(twice)

    return F.pmod(F.aggregate(F.sequence(F.lit(1), n), F.lit(0), step), F.lit(10)) == 0


def _passes(kind: str, hit: Column) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    if kind == "ip":
        return ~F.exists(F.split(hit, r"\.", -1), lambda p: F.length(F.regexp_replace(p, "^0+", "")).cast("int") > 3) & F.forall(F.split(hit, r"\.", -1), lambda p: F.regexp_replace(p, "^0+(?=.)", "").cast("double") <= 255)
    if kind == "card":
        return F.when(F.length(digits).between(16, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    return F.lit(True)


def _digits(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def _vote(for_: Column, against: Column) -> Column:
    """1 for, -1 against, 0 no opinion (neither, or both)."""
    return F.coalesce(for_.cast("int"), F.lit(0)) - F.coalesce(against.cast("int"), F.lit(0))


def _named(words: str, before: bool) -> str:
    """One of the words next to the span, or one word away from it."""
    some = "|".join(w.replace("+", r"\+") for w in words.split())
    return rf"(?:^|[^a-z0-9@])(?:{some})[^a-z0-9]{{1,4}}(?:[a-z]{{1,8}}[^a-z0-9]{{1,3}})?$" if before else rf"^[^a-z0-9]{{0,4}}(?:[a-z]{{1,8}} )?(?:{some})(?:[^a-z0-9]|$)"


def _name_and_value(hit: Column) -> tuple[Column, Column]:
    """What a secret is given to, in lower case, or nothing; and the secret itself."""
    name = F.lower(F.regexp_extract(hit, r"^([A-Za-z_][A-Za-z0-9_-]*)\s{0,2}[=:]", 1))
    return name, F.regexp_replace(hit, r"^[A-Za-z_][A-Za-z0-9_-]*\s{0,2}[=:]\s{0,2}[\x22']?", "")


def _own_votes(kind: str, hit: Column) -> list[Column]:
    """Shape, check and gazetteer, which look at the span itself."""
    digits = _digits(hit)
    n, of_digits = F.length(hit), F.length(digits)
    if kind == "email":
        return [_vote(n.between(6, 80), n > 80), _vote(hit.rlike(r"\.[A-Za-z]{2,}$"), ~hit.rlike(r"\.[A-Za-z]{2,}$")), _vote(F.lower(F.regexp_extract(hit, r"\.([A-Za-z0-9-]+)$", 1)).isin(*TOP_LEVEL), F.lit(False))]
    if kind == "ip":
        return [_vote(~hit.rlike(r"(^|\.)0[0-9]"), hit.rlike(r"(^|\.)0[0-9]")), _vote(F.lit(False), hit.rlike(r"^(0|255)\.")), _vote(hit.rlike(r"^(10|127|192\.168|169\.254)\."), F.lit(False))]
    if kind == "card":
        start = F.substring(digits, 1, 6).cast("int")
        issued = F.lit(False)
        for low, high in ISSUERS:
            issued = issued | start.between(low, high)
        return [_vote(of_digits == 16, F.lit(False)), _vote(F.lit(True), F.lit(False)), _vote(issued, ~issued)]
    if kind == "phone":
        code = F.substring(digits, 1, 1).isin(*CALLING_CODES) | F.substring(digits, 1, 2).isin(*CALLING_CODES) | F.substring(digits, 1, 3).isin(*CALLING_CODES)
        return [_vote(of_digits.between(10, 13), F.lit(False)), _vote(of_digits >= 9, of_digits < 9), _vote(code, ~code)]
    if kind == "secret":
        name, value = _name_and_value(hit)
        mixed = value.rlike("[A-Za-z]") & value.rlike("[0-9]")
        plain = value.rlike(r"^[A-Za-z]+[.,;:!?)]*$") | value.rlike(r"^[0-9.,:/ -]+$") | value.rlike(r"://|@|/.*/|\.(png|jpg|gif|html?|pdf|zip|txt|js|css)\b")
        turns = F.length(F.regexp_replace(F.regexp_replace(value, "[A-Za-z]+", "a"), "[0-9]+", "0"))
        begun = F.lit(False)
        for p in PREFIXES:
            begun = begun | value.startswith(p)
        return [_vote(mixed & (F.length(value) >= 16), plain), _vote(begun | (turns >= 8), value.rlike(r"^[0-9A-Fa-f]{8}(-[0-9A-Fa-f]{4}){3}-[0-9A-Fa-f]{12}$") | (turns < 4)), _vote(name.isin(*CREDENTIAL_NAMES), name.isin(*OTHER_NAMES))]
    dated = hit.rlike(r"^(19|20)[0-9]{2}[ .-][01]?[0-9][ .-][0-3]?[0-9]$") | hit.rlike(r"^[0-3]?[0-9][ .-][01]?[0-9][ .-](19|20)[0-9]{2}$") | hit.rlike(r"^(19|20)[0-9]{2}[ -](19|20)[0-9]{2}$")
    laid = hit.rlike(r"^\([2-9][0-9]{2}\) ?[0-9]{3}[ .-][0-9]{4}$|^[2-9][0-9]{2}([ .-])[0-9]{3}\1[0-9]{4}$|^\(?0[1-9][0-9]{1,3}\)?[ .-][0-9]{3,4}[ .-]?[0-9]{2,4}$")
    area = (of_digits == 10) & digits.rlike("^[2-9](?!11)[0-9]{2}[2-9](?!11)") | (of_digits.between(9, 11) & digits.rlike("^0[1-9]"))
    return [_vote(laid, dated | ~hit.rlike("[ .()-]")), _vote(of_digits.between(9, 11), ~of_digits.between(7, 12)), _vote(area, (of_digits == 10) & ~area)]


def _passes(kind: str, hit: Column) -> Column:
    digits = _digits(hit)
    if kind == "ip":
        return ~F.exists(F.split(hit, r"\.", -1), lambda p: F.length(F.regexp_replace(p, "^0+", "")).cast("int") > 3) & F.forall(F.split(hit, r"\.", -1), lambda p: F.regexp_replace(p, "^0+(?=.)", "").cast("double") <= 255)
    if kind == "card":
        return F.when(F.length(digits).between(16, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    if kind == "contact":
        return F.length(digits).between(7, 12)
    return F.lit(True)


def _proposals(kind: str, text: Column) -> Column:
    def full(x: Column) -> Column:
        hit, start = x["hit"], x["start"]
        n, digits = F.length(hit), F.length(_digits(hit))
        around = [_vote(x["before"].rlike(_named(BEFORE[kind][0], True)), x["before"].rlike(_named(BEFORE[kind][1], True))), _vote(x["after"].rlike(_named(AFTER[kind][0], False)), x["after"].rlike(_named(AFTER[kind][1], False)))]
        votes = [v.cast("int").alias(k) for k, v in zip(VOTES, [*_own_votes(kind, hit), *around], strict=True)]
        shapes = (n >= 20, digits * 2 >= n, hit.rlike("[A-Za-z].*[0-9]|[0-9].*[A-Za-z]"), hit.rlike("[a-z].*[A-Z]|[A-Z].*[a-z]"), hit.rlike("[ .()-]"))
        return F.struct(F.lit(kind).alias("kind"), start.alias("start"), (start + n).alias("end"), *votes, *(c.cast("int").alias(k) for k, c in zip(SHAPES, shapes, strict=True)))

    return F.transform(F.filter(_found(kind, text), lambda x: _passes(kind, x["hit"])), full)


@dataclass(frozen=True)
class SpanModel:
    """Log-odds weights for each kind: a bias, one for each labeler's votes for and against, one for each shape."""

    weights: dict[str, list[float]]
    reliability: dict[str, list[float]]
    prior: dict[str, float]
    proposed: dict[str, int]

    def score(self, span: Column) -> Column:
        total = F.lit(0.0)
        for kind, w in self.weights.items():
            each = [(span[f] == v).cast("double") for f in VOTES for v in (1, -1)] + [span[f].cast("double") for f in SHAPES]
            mine = sum((x * float(v) for x, v in zip(each, w[1:], strict=True)), F.lit(float(w[0])))
            total = F.when(span["kind"] == kind, mine).otherwise(total)
        return 1 / (1 + F.exp(-total))


def _columns(x: np.ndarray) -> np.ndarray:
    """What the classifier sees: each vote for and against as a column of its own, then the shapes."""
    votes = x[:, : len(VOTES)]
    return np.column_stack([*(votes[:, k] == v for k in range(len(VOTES)) for v in (1, -1)), *x[:, len(VOTES) :].T]).astype(float)


def expectation_maximisation(votes: np.ndarray, counts: np.ndarray, rounds: int = 200) -> tuple[np.ndarray, np.ndarray, float]:
    """Two classes; given the class, each labeler votes for, against or not with chances of its own, apart from the others.

    Returns each pattern's probability of being real, each labeler's reliability (how often a vote is right) and
    how many are real.  Starts from sums of votes; a few imagined votes keep chances off 0 and 1 and stand in for
    labelers that hardly vote.
    """
    p = 1 / (1 + np.exp(-(1.5 * votes.sum(1) - 0.5)))
    cast = np.stack([votes == v for v in (1, 0, -1)], 2).astype(float)  # patterns, labelers, votes
    imagined = {1: np.array([4.0, 4.0, 1.0]), 0: np.array([1.0, 4.0, 4.0])}
    for _ in range(rounds):
        prior = float((counts @ p + 1) / (counts.sum() + 2))
        logs, chances = {}, {}
        for y, w in ((1, counts * p), (0, counts * (1 - p))):
            seen = np.einsum("i,ilv->lv", w, cast) + imagined[y]
            chances[y] = seen / seen.sum(1, keepdims=True)
            logs[y] = np.einsum("ilv,lv->i", cast, np.log(chances[y]))
        odds = np.log(prior / (1 - prior)) + logs[1] - logs[0]
        new = 1 / (1 + np.exp(-np.clip(odds, -30, 30)))
        done = np.abs(new - p).max() < 1e-9
        p = new
        if done:
            break
    right = prior * chances[1][:, 0] + (1 - prior) * chances[0][:, 2]
    wrong = prior * chances[1][:, 2] + (1 - prior) * chances[0][:, 0]
    return p, right / (right + wrong), prior


def _logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, rounds: int = 30, ridge: float = 1.0) -> np.ndarray:
    """Newton steps on weighted soft labels with a ridge."""
    a = np.column_stack([np.ones(len(x)), x])
    w = np.zeros(a.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        g = a.T @ (weight * (p - y)) + ridge * w
        h = (a * (weight * p * (1 - p))[:, None]).T @ a + ridge * np.eye(len(w))
        w = w - np.linalg.solve(h, g)
    return w


def learned(rows: np.ndarray, counts: np.ndarray) -> tuple[list[float], list[float], float]:
    """Weights, reliabilities and prior of one kind, from the votes and shapes of each pattern and how often it occurs."""
    p, reliability, prior = expectation_maximisation(rows[:, : len(VOTES)], counts)
    return [float(v) for v in _logistic(_columns(rows), p, np.minimum(counts, 1e6), ridge=0.1)], [float(v) for v in reliability], prior


def fit(proposed: DataFrame, spans: str = "spans") -> SpanModel:
    """Learns from counts of what was proposed in all rows; ``spans`` as given by :func:`propose`."""
    fields = ["kind", *FEATURES]
    seen = proposed.select(F.explode(spans).alias("s")).select(*(F.col(f"s.{f}").alias(f) for f in fields)).groupBy(*fields).count().collect()
    weights, reliability, prior, total = {}, {}, {}, {}
    for kind in KINDS:
        rows = [r for r in seen if r["kind"] == kind]
        total[kind] = sum(r["count"] for r in rows)
        if not rows:  # nothing to learn from and nothing to decide
            weights[kind], reliability[kind], prior[kind] = [0.0] * (1 + 2 * len(VOTES) + len(SHAPES)), [0.8] * len(VOTES), 0.5
            continue
        weights[kind], reliability[kind], prior[kind] = learned(np.array([[r[f] for f in FEATURES] for r in rows], float), np.array([r["count"] for r in rows], float))
    return SpanModel(weights, reliability, prior, total)


def propose(docs: DataFrame, text_col: str = "text", into: str = "spans") -> DataFrame:
    """All columns, and the one named ``into``: what the patterns propose, kind by kind in the order of KINDS, then by start."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    return docs.withColumn(into, F.concat(*(_proposals(k, text) for k in KINDS)))


def find(docs: DataFrame, text_col: str = "text", carry: tuple[str, ...] = ("doc_id",), threshold: float = 0.5, into: str = "spans") -> tuple[DataFrame, SpanModel]:
    """``carry`` columns and the spans that stay (kind, start, end, score, base), and the model that was learned.

    The texts are searched twice, once to learn and once for the result, so nothing of them is written.
    """
    kept = [quoted(c) for c in carry]
    proposed = propose(docs.select(*kept, *([] if text_col in carry else [quoted(text_col)])), text_col, into)
    model = fit(proposed, into)
    scored = F.transform(into, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), model.score(s).alias("score"), s["kind"].isin(*BASE).alias("base")))
    return proposed.withColumn(into, F.filter(scored, lambda s: s["base"] | (s["score"] >= threshold))).select(*kept, into), model


def described(spans: Column) -> Column:
    """kind:start:end, comma-joined in order."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


#: Code points in one block of a text that is cut up.
BLOCK = 2048


def redact(text: Column, spans: Column) -> Column:
    """The text with each span as its kind in brackets; spans that overlap go as one, under the kind that begins first, the longer of equals.

    The text is cut into blocks once, so a span costs a block and not the text before it.
    """
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("minus_end"), s["kind"].alias("kind"))))

    def joined(v: Column) -> Column:
        earlier = F.concat(F.array(F.lit(0)), F.slice(v["reach"], F.lit(1), F.size(v["reach"]) - 1))
        heads = F.filter(F.arrays_zip(v["spans"].alias("span"), earlier.alias("before")), lambda x: x["span"]["start"] >= x["before"])

        def between(begin: Column, end: Column) -> Column:
            """Code points begin to end, exclusive."""
            first, last = F.floor(begin / BLOCK).cast("int"), F.floor(end / BLOCK).cast("int")
            head, tail = F.coalesce(F.get(v["blocks"], first), F.lit("")), F.coalesce(F.get(v["blocks"], last), F.lit(""))
            at = F.pmod(begin, F.lit(BLOCK)) + 1
            inside = F.substring(head, at, end - begin)
            across = F.concat(F.substring(head, at, F.lit(BLOCK)), F.array_join(F.slice(v["blocks"], first + 2, F.greatest(last - first - 1, F.lit(0))), ""), F.substring(tail, F.lit(1), F.pmod(end, F.lit(BLOCK))))
            return F.when(first == last, inside).otherwise(across)

        # what precedes the first span of a group begins where the groups before end, which that span knows
        parts = F.transform(heads, lambda x: F.concat(between(x["before"], x["span"]["start"]), F.lit("<"), F.upper(x["span"]["kind"]), F.lit(">")))
        return F.concat(F.array_join(parts, ""), between(F.element_at(v["reach"], -1), v["size"]))

    def reached(v: Column) -> Column:
        reach = running(F.transform(v["spans"], lambda s: -s["minus_end"]), lambda x, y: F.greatest(x, y))
        return _let(F.struct(v["spans"].alias("spans"), reach.alias("reach"), v["blocks"].alias("blocks"), v["size"].alias("size")), joined)

    blocks = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{BLOCK}}}+"), F.lit(0))
    made = _let(F.struct(ordered.alias("spans"), blocks.alias("blocks"), F.length(text).alias("size")), reached)
    return F.when(F.size(spans) == 0, text).otherwise(made)
