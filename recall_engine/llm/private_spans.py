"""Personal data by weak supervision (DataFrame functions only).

Base patterns give spans that always stand. Looser patterns give candidates of every kind: long mixed tokens, phone numbers
without a country code, numbers of 13 to 15 digits with a card's check digit (others are known non-cases), addresses without
a dot or with "(at)" and "(dot)", and IP addresses of version 6 or with bracketed dots. Labelers vote on every span, for, against or not at all: its shape, a gazetteer of words
before it, the punctuation before it, its mix of characters, and signs of made-up numbers. Votes are counted per
pattern of votes, of which there is a fixed number; on these counts expectation-maximisation estimates how reliable each
labeler is, with base spans as known cases and failed base matches as known non-cases, and a logistic span classifier is
trained on the resulting probabilities. Its weights go back into a column expression, and candidates of probability one
half and more that touch no base span become spans.

Spans are places in code points, end exclusive. Java's matcher tells no places, so they come from lengths: the texts
between matches (split) and the matches (extract) alternate.

Defined results: null or empty text has no spans; repeated rows have equal results; a text's time grows with its length and
the number of its matches, but for one step a match for each STEP^2 matches; other columns, whatever their names, are not
read; an empty table gives an empty result; without any candidate nothing is trained and the base spans are the result.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .scratch import cut

# The base patterns, written so that each start is tried once; they match as the plain ones do, except that
# chains of other than 16 to 19 digits are passed over at once.
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){15,18}(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_OCTET = "(?:25[0-5]|2[0-4][0-9]|[01]?[0-9]?[0-9])"
LOOSE = {
    "secret": r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]*+[0-9])(?=[0-9_-]*+[A-Za-z])[A-Za-z0-9_-]{16,}+",
    "phone": r"(?<![0-9+(.-])(?:\([0-9]{3}\)\x20?|[0-9]{3}[.\x20-])[0-9]{3}[.\x20-][0-9]{4}(?![0-9])",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){12,14}(?![\x20-]?[0-9])",
    "email": r"(?<![A-Za-z0-9._%+@-])[A-Za-z0-9._%+-]++(?:@|\x20?[\[(](?i:at)[\])]\x20?)[A-Za-z0-9-]++(?:(?:\.|\x20?[\[(](?i:dot)[\])]\x20?)[A-Za-z0-9-]++)*+(?!@)",
    "ip": rf"(?<![0-9A-Za-z:.\]])(?:{_OCTET}(?:\[\.\]{_OCTET}){{3}}(?![0-9])|(?=[A-Fa-f:]*+[0-9])(?:(?:[0-9A-Fa-f]{{1,4}}:){{7}}[0-9A-Fa-f]{{1,4}}|(?:[0-9A-Fa-f]{{1,4}}:){{1,6}}(?::[0-9A-Fa-f]{{1,4}}){{1,6}})(?![0-9A-Za-z:]))",
}
#: What a text must contain for a pattern to be tried: this or, without one, a digit.
NEEDS = {"email": "@", "phone": "+"}
LOOSE_NEEDS = {"email": ""}
KINDS = ("email", "ip", "card", "phone", "secret")
CONTEXT_CHARS = 24
#: Elements that one step of a running sum takes together.
STEP = 64

GAZETTEER = {
    "email": r"\b(?:e-?mail|mail|contact|kontakt|correo|courriel)\b",
    "ip": r"\b(?:ip|host|server|address|adresse)\b",
    "card": r"\b(?:card|credit|visa|mastercard|karte|tarjeta|carte|iban|account)\b",
    "phone": r"\b(?:tel|phone|fon|telefon|call|mobile|fax|cell)\b",
    "secret": r"(?:token|passw|passwd|pwd|secret|api|key|auth|bearer|credential)",
}
SHAPE = {"secret": r"^(?:AKIA[0-9A-Z]{16}|[0-9a-f]{16,64})$", "phone": r"^\([0-9]{3}\)", "email": r"\.[A-Za-z]{2,}$", "ip": r"^(?!0)", "card": r"^[0-9]{16}$|^[0-9]{4}([\x20-])[0-9]{4}\1"}
LABELERS = ("shape", "gazetteer", "punctuation", "mixture", "invented")
ITERATIONS = 60


def raw_matches(text: Column, pattern: str, needs: str | None) -> tuple[Column, Column]:
    """The matches, and the texts between them if there are any."""
    some = F.contains(text, F.lit(needs)) if needs is not None else text.rlike("[0-9]")
    empty = F.array().cast("array<string>")
    return F.when(some, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(empty), F.split(text, pattern, -1)


def _bound(value: Column, f: Callable[[Column], Column]) -> Column:
    """f(value) with the value computed once, not at each place where f has it."""
    return F.element_at(F.transform(F.array(value), f), 1)


def running(values: Column, zero: Column, fold: Callable[[Column, Column], Column]) -> Callable[[Callable[[Callable[[Column], Column]], Column]], Column]:
    """For ``use``: the column that it makes from ``at``, where at(k) folds the first k of ``values``. Values are folded by
    STEP and STEP^2 beforehand, so a place costs at most 2 STEP steps and one for each STEP^2 values before it."""

    def shorter(x: Column) -> Column:
        n = F.size(x)
        index = F.when(n > 0, F.sequence(F.lit(0), F.floor((n - 1) / F.lit(STEP)).cast("int"))).otherwise(F.array().cast("array<int>"))
        return F.transform(index, lambda i: F.aggregate(F.slice(x, i * STEP + 1, F.lit(STEP)), zero, fold))

    def column(use: Callable[[Callable[[Column], Column]], Column]) -> Column:
        def with_levels(x0: Column, x1: Column, x2: Column) -> Column:
            def at(k: Column) -> Column:
                one, two = F.shiftright(k, 6), F.shiftright(k, 12)
                done = F.aggregate(F.slice(x2, F.lit(1), two), zero, fold)
                done = F.aggregate(F.slice(x1, two * STEP + 1, one - two * STEP), done, fold)
                return F.aggregate(F.slice(x0, one * STEP + 1, k - one * STEP), done, fold)

            return use(at)

        return _bound(values, lambda x0: _bound(shorter(x0), lambda x1: _bound(shorter(x1), lambda x2: with_levels(x0, x1, x2))))

    return column


def placed(found: Column, gaps: Column) -> Column:
    """array of (start, end, m, left, right)."""
    empty = F.array().cast("array<struct<start:int,end:int,m:string,left:string,right:string>>")

    def spans(found: Column, gaps: Column) -> Column:
        index = F.sequence(F.lit(0), F.size(found) - 1)
        lengths = F.zip_with(F.slice(gaps, F.lit(1), F.size(found)), found, lambda g, m: F.char_length(g) + F.char_length(m))

        def one(at: Callable[[Column], Column], k: Column) -> Column:
            m, gap = F.element_at(found, k + 1), F.element_at(gaps, k + 1)
            return _bound(at(k) + F.char_length(gap), lambda start: F.struct(start.alias("start"), (start + F.char_length(m)).alias("end"), m.alias("m"), F.right(gap, F.lit(CONTEXT_CHARS)).alias("left"), F.left(F.element_at(gaps, k + 2), F.lit(CONTEXT_CHARS)).alias("right")))

        return running(lengths, F.lit(0), lambda a, x: a + x)(lambda at: F.transform(index, lambda k: one(at, k)))

    return F.when(F.size(found) > 0, _bound(found, lambda f: _bound(gaps, lambda g: spans(f, g)))).otherwise(empty)


def free_of_base(spans: Column) -> Column:
    """``spans`` without the candidates that touch a base span, sorted by start."""

    def kept(s: Column) -> Column:
        """Base spans that start no later end by the largest end before; of those that start later the next one is first."""
        n = F.size(s)
        ends = F.transform(s, lambda x: F.when(x["known"] == 1, x["end"]).otherwise(0))
        far = F.lit(1 << 30)
        starts = F.reverse(F.transform(s, lambda x: F.when(x["known"] == 1, x["start"]).otherwise(far)))
        before = running(ends, F.lit(0), lambda a, x: F.greatest(a, x))
        after = running(starts, far, lambda a, x: F.least(a, x))
        return before(lambda most: after(lambda least: F.filter(s, lambda x, i: (x["known"] >= 0) | ((most(i) <= x["start"]) & (least(n - i - 1) >= x["end"])))))

    # Sorted by start, base spans first, so that an equal start counts as before.
    order = F.array_sort(F.transform(spans, lambda x: F.struct(x["start"].alias("start"), (-x["known"]).alias("rank"), x["at"].alias("at"), x["end"].alias("end"), x["kind"].alias("kind"), x["votes"].alias("votes"), x["known"].alias("known"))))
    return F.when(F.exists(spans, lambda x: x["known"] == -1) & F.exists(spans, lambda x: x["known"] == 1), _bound(order, kept)).otherwise(order)


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def luhn(m: Column) -> Column:
    back = F.reverse(_digits(m))

    def value(i: Column) -> Column:
        d = F.substring(back, i, F.lit(1)).try_cast("int")
        twice = F.when(d > 4, 2 * d - 9).otherwise(2 * d)
        return F.when(i % 2 == 0, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.char_length(back)), F.lit(0), lambda a, i: a + value(i)) % 10 == 0


def valid(kind: str, m: Column) -> Column:
    """Whether a base match stands."""
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: F.coalesce(F.substring(F.regexp_replace(p, "^0+", ""), 1, 4).try_cast("int"), F.lit(0)) <= 255)
    if kind == "card":
        return luhn(m)
    if kind == "phone":
        return F.char_length(_digits(m)).between(8, 15)
    return F.lit(True)


def votes(kind: str, span: Column) -> Column:
    """Each labeler's vote (1, 0 or -1), packed in base 3."""
    m, left = span["m"], F.lower(span["left"])
    digits = F.char_length(_digits(m)) / F.char_length(m)
    each = [
        F.when(m.rlike(SHAPE[kind]), 1).otherwise(-1 if kind == "secret" else 0),
        F.when(left.rlike(GAZETTEER[kind]), 1).otherwise(0),
        F.when(left.rlike(r"""[=:][\x20]?["']?$"""), 1).when(left.rlike(r"[a-z0-9_-]$"), -1).otherwise(0),
        F.when(digits.between(0.15, 0.95) if kind == "secret" else digits > 0.5, 1).otherwise(-1 if kind == "secret" else 0),
        F.when(_digits(m).rlike(r"([0-9])\1{5}|0123456|1234567|9876543"), -1).otherwise(0),
    ]
    return reduce(lambda a, v: a * 3 + v + 1, each, F.lit(0)).cast("int")


def unpacked(code: int) -> list[int]:
    out = []
    for _ in LABELERS:
        code, v = divmod(code, 3)
        out.append(v - 1)
    return out[::-1]


class SpanClassifier:
    """Weights by kind and vote; ``bias[kind] + sum of weight[labeler, vote]`` is a span's log-odds."""

    def __init__(self, bias: dict[str, float], weight: dict[tuple[int, int], float], reliability: dict[tuple[int, int], tuple[float, float]]):
        self.bias, self.weight, self.reliability = bias, weight, reliability

    def probability(self, kind: str, code: int) -> float:
        z = self.bias[kind] + sum(self.weight[j, v] for j, v in enumerate(unpacked(code)))
        return 1 / (1 + math.exp(-max(-50.0, min(50.0, z))))


def trained(counts: list[tuple[str, int, int, int]], iterations: int = ITERATIONS) -> SpanClassifier:
    """From (kind, votes, known, n), known being 1, 0 or -1 for not known: labelers' reliabilities by EM, then the classifier by weighted gradient steps."""
    values = [(j, v) for j in range(len(LABELERS)) for v in (-1, 0, 1)]
    rows = [(kind, unpacked(code), known, float(n)) for kind, code, known, n in counts]
    # Known cases far outnumber candidates and must not drown them: each side weighs as much as the unknown, at most.
    unknown = sum(n for *_, known, n in rows if known < 0)
    scale = {k: min(1.0, max(unknown, 1.0) / max(sum(n for *_, known, n in rows if known == k), 1.0)) for k in (0, 1)} | {-1: 1.0}
    rows = [(kind, v, known, n * scale[known]) for kind, v, known, n in rows]
    p = [float(known) if known >= 0 else 1 / (1 + math.exp(-1.5 * sum(v))) for _, v, known, _ in rows]
    share = {}
    for _ in range(iterations):
        like = {}
        for y in (0, 1):
            mass = sum((q if y else 1 - q) * n for q, (_, _, _, n) in zip(p, rows, strict=True))
            for j, v in values:
                hit = sum((q if y else 1 - q) * n for q, (_, votes_, _, n) in zip(p, rows, strict=True) if votes_[j] == v)
                # The prior holds that labelers do better than chance, which decides where few spans were seen.
                agrees = {(1, 1): 3, (-1, 0): 3, (0, 0): 2, (0, 1): 2}.get((v, y), 1)
                like[j, v, y] = (hit + agrees) / (mass + 6)
        for k in KINDS:
            own = [(q, n) for q, (kind, _, known, n) in zip(p, rows, strict=True) if kind == k]
            share[k] = (sum(q * n for q, n in own) + 1) / (sum(n for _, n in own) + 2)
        for i, (kind, v, known, _) in enumerate(rows):
            if known < 0:
                z = math.log(share[kind] / (1 - share[kind])) + sum(math.log(like[j, x, 1] / like[j, x, 0]) for j, x in enumerate(v))
                p[i] = 1 / (1 + math.exp(-max(-50.0, min(50.0, z))))
    bias, weight = dict.fromkeys(KINDS, 0.0), dict.fromkeys(values, 0.0)
    total = sum(n for *_, n in rows) or 1.0
    for _ in range(400):
        step_b, step_w = dict.fromkeys(KINDS, 0.0), dict.fromkeys(values, 0.0)
        for q, (kind, v, _, n) in zip(p, rows, strict=True):
            z = bias[kind] + sum(weight[j, x] for j, x in enumerate(v))
            g = (q - 1 / (1 + math.exp(-max(-50.0, min(50.0, z))))) * n / total
            step_b[kind] += g
            for j, x in enumerate(v):
                step_w[j, x] += g
        bias = {k: b + 2.0 * (step_b[k] - 1e-3 * b) for k, b in bias.items()}
        weight = {k: w + 2.0 * (step_w[k] - 1e-3 * w) for k, w in weight.items()}
    return SpanClassifier(bias, weight, {(j, v): (like[j, v, 0], like[j, v, 1]) for j, v in values} if rows else {})


def voted(docs: DataFrame) -> DataFrame:
    """(doc_id, text) to (doc_id, spans): every match with kind, start, end, votes and ``known``: 1 base, 0 a base match or a card-like number that fails, -1 a candidate."""
    t = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("t"))
    patterns = [(f"b_{k}", k, p, NEEDS.get(k)) for k, p in BASE.items()] + [(f"l_{k}", k, p, LOOSE_NEEDS.get(k)) for k, p in LOOSE.items()]
    names = [n for n, *_ in patterns]
    for name, _, pattern, needs in patterns:
        t = t.withColumn(name, raw_matches(F.col("t"), pattern, needs)[0])
    some = {n: F.size(n) > 0 for n in names}
    t = t.withColumns({f"g_{n}": F.when(some[n], F.split("t", p, -1)).otherwise(F.array().cast("array<string>")) for n, _, p, _ in patterns}).drop("t")
    # One expression places the matches of all patterns; an expression each would only take long to plan.
    each = F.array(*[F.struct(F.col(n).alias("found"), F.col(f"g_{n}").alias("gaps")) for n in names])
    t = t.select("doc_id", F.transform(each, lambda x: placed(x["found"], x["gaps"])).alias("placed"))

    def described(name: str, kind: str) -> Column:
        known = (lambda s: F.when(valid(kind, s["m"]), 1).otherwise(0)) if name.startswith("b_") else (lambda s: F.when(luhn(s["m"]), -1).otherwise(0) if kind == "card" else F.lit(-1))
        return F.transform(F.col("placed")[names.index(name)], lambda s: F.struct(F.lit(kind).alias("kind"), F.lit(KINDS.index(kind)).alias("at"), s["start"].alias("start"), s["end"].alias("end"), votes(kind, s).alias("votes"), known(s).alias("known")))

    every = t.select("doc_id", F.flatten(F.array(*[described(n, k) for n, k, *_ in patterns])).alias("spans"))
    # A candidate that touches a base span is part of it.
    return every.select("doc_id", free_of_base(F.col("spans")).alias("spans"))


def joined_spans(spans: Column) -> Column:
    order = F.array_sort(F.transform(spans, lambda s: F.struct(s["at"].alias("at"), s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    return F.array_join(F.transform(order, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def found(docs: DataFrame, text: str = "text", doc_id: str = "doc_id") -> DataFrame:
    """doc_id, base (array of base spans) and all_spans (with the accepted candidates) of each row; a span has kind, start and end."""
    v = cut(voted(docs.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text"))))
    each = v.where(F.size("spans") > 0).select(F.explode("spans").alias("s"))
    counts = [(r.kind, r.votes, r.known, r.n) for r in each.groupBy("s.kind", "s.votes", "s.known").agg(F.count("*").alias("n")).collect()]  # at most kinds * 3^labelers * 3 rows
    model = trained(sorted(counts))
    accepted = [f"{k}:{c}" for k, c, known, _ in sorted(counts) if known < 0 and model.probability(k, c) >= 0.5]
    stands = F.filter("spans", lambda s: (s["known"] == 1) | ((s["known"] == -1) & F.array_contains(F.lit(accepted) if accepted else F.array().cast("array<string>"), F.concat_ws(":", s["kind"], s["votes"].cast("string")))))
    return v.select("doc_id", F.filter("spans", lambda s: s["known"] == 1).alias("base"), stands.alias("all_spans"))


def digest(spans: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans."""
    def number(kind: str) -> Column:
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [number(k) for k in BASE]
    return spans.select("doc_id", *counts, F.sha2(joined_spans(F.col("base")), 256).alias("base_sha256"), joined_spans(F.col("all_spans")).alias("spans"))
