"""Personal data by weak supervision (DataFrame functions only on the data's path).

1. Patterns propose spans: the base kinds, which are always kept, and looser kinds, which need a verdict.
2. Labelers (check digits and rules of form, gazetteers, context words, borders, shape) vote 1, 0 or -1 on every span.
3. The votes are counted by pattern of votes. There are at most 3^labelers patterns a kind, however large
   the corpus is; expectation-maximisation over these counts estimates each labeler's reliability for each kind.
4. The posteriors train a logistic span classifier of each kind over the votes; it decides on the looser spans.

Defined cases: a null text is an empty one; without any span spans is empty and the digest that of the
empty string; repeated rows are judged each by itself; an empty table trains nothing and gives no rows.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import spans as S
from .common import stored

#: The base kinds in their order.
KINDS = ["email", "ip", "card", "phone"]
LOOSE = ["tel", "ssn", "iban", "name"]
LOCAL = "[A-Za-z0-9._%+-]"
PATTERNS = {
    "email": rf"(?:\G|(?<!{LOCAL})){LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?+[0-9]){11,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "tel": r"(?<![0-9+.-])\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}(?![0-9.-])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}(?:\x20?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "name": r"(?<![A-Za-z])(?:Mr|Mrs|Ms|Dr|Prof|Herr|Frau|Mme|Sr|Sra)\.?\x20[A-Z][a-z]{2,20}(?:\x20[A-Z][a-z]{2,20})?(?![a-z])",
}
#: Common first names of the four languages, for names with a title.
FIRST_NAMES = (
    "Anna Maria Peter Hans Klaus Julia Sabine Thomas Michael Stefan Andreas Ursula John Mary James Robert Linda David Susan Paul Sarah Emma William "
    "Jean Pierre Marie Michel Sophie Claire Nicolas Camille Luc Jose Juan Carmen Luis Ana Carlos Lucia Pedro Elena Miguel"
).split()
#: Gazetteers and context words, as patterns over a span's own text and what stands before it; kinds not named abstain.
KNOWN = {
    "email": r"\.(?:com|org|net|edu|gov|de|fr|es|uk|io)$", "ip": r"^(?!0|127\.|255\.)", "card": r"^(?:4|5[1-5]|2[2-7]|3[47]|6)", "phone": r"^\+(?:1|33|34|44|49)(?![0-9]{13})",
    "iban": r"^(?:DE|FR|ES|GB|IT|NL|BE|AT|CH|PT)", "name": r"\x20(?:" + "|".join(FIRST_NAMES) + r")\b",
}
#: What the form alone says, apart from what the pattern or the base check demand; kinds not named abstain.
STRICT = {
    "email": r"^(?!\.)(?!.*\.\.)[^@]*[^.@]@(?!-)", "ip": r"^(?!.*(?:^|\.)0[0-9])", "tel": r"^\(?[2-9][0-9]{2}\)?[\x20.-][2-9]",
    "ssn": r"^(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)",
}
CONTEXT = {
    "email": "mail|contact|write|@", "ip": "addr|host|ip|server|from", "card": "card|visa|pay|account", "phone": "call|tel|phone|mobile|fax",
    "tel": "call|tel|phone|mobile|fax", "ssn": "ssn|social|security", "iban": "iban|bank|konto|account", "name": "dear|from|by|contact|regards|signed",
}
LABELERS = ["strict", "known", "context", "border", "shape"]


def _valid(kind: str):
    n = lambda v: F.char_length(S.digits(v))
    part = lambda p: F.regexp_replace(p, "^0+(?=[0-9])", "")
    return {
        "ip": lambda v: F.forall(F.split(v, r"\."), lambda p: (F.char_length(part(p)) <= 3) & (F.right(part(p), F.lit(3)).cast("int") <= 255)),
        "card": lambda v: F.when(n(v).between(12, 19), S.luhn(S.digits(v))).otherwise(False),
        "phone": lambda v: n(v).between(9, 15),
    }.get(kind, lambda v: F.lit(True))


def mod97(v: Column) -> Column:
    """Whether an account number's letters and digits pass the check modulo 97: its first four characters go last,
    letters count 10 to 35."""
    plain = F.translate(v, " ", "")
    turned = F.concat(F.substr(plain, F.lit(5)), F.left(plain, F.lit(4)))

    def step(acc: Column, i: Column) -> Column:
        d = F.ascii(F.substr(turned, i, F.lit(1)))
        return F.when(d >= 65, acc * 100 + d - 55).otherwise(acc * 10 + d - 48) % 97

    return F.aggregate(F.sequence(F.lit(1), F.char_length(turned)), F.lit(0), step) == 1


def _votes(kind: str, s: Column) -> list[Column]:
    sign = lambda c: F.when(c, 1).otherwise(-1)
    v, before, after = s["value"], F.lower(s["before"]), s["after"]
    even = {"card": F.char_length(v) == 16, "email": F.char_length(v) < 64, "name": F.char_length(v) > 6}.get(kind, ~F.rlike(v, F.lit(r"([0-9])\1{4}")))
    strict = sign(mod97(v)) if kind == "iban" else sign(F.rlike(v, F.lit(STRICT[kind]))) if kind in STRICT else F.lit(0)
    return [
        strict, sign(F.rlike(v, F.lit(KNOWN[kind]))) if kind in KNOWN else F.lit(0), F.when(F.rlike(before, F.lit(CONTEXT[kind])), 1).otherwise(0),
        sign(~F.rlike(before, F.lit(r"[\p{L}0-9]$")) & ~F.rlike(after, F.lit(r"^[\p{L}0-9]"))), sign(even),
    ]


def propose(docs: DataFrame, text: str = "text") -> DataFrame:
    """Adds _spans: every proposed span with its kind, its rank in the order of kinds and its votes."""
    whole, kinds = F.coalesce(F.col(text), F.lit("")), KINDS + LOOSE

    def of(kind: str) -> Column:
        found = S.find(whole, PATTERNS[kind], _valid(kind))
        return F.transform(found, lambda s: F.struct(
            s["start"].alias("start"), F.lit(kinds.index(kind)).alias("rank"), s["end"].alias("end"), F.lit(kind).alias("kind"),
            *(v.cast("int").alias(n) for n, v in zip(LABELERS, _votes(kind, s), strict=True)),
        ))

    return docs.withColumn("_spans", F.concat(*(of(k) for k in kinds)))


def reliabilities(counts: list[dict], rounds: int = 60) -> tuple[dict, dict]:
    """EM over vote patterns, each kind by itself. counts: rows with kind, the votes and n. Returns for every kind and
    labeler the probabilities of its votes by truth, {(truth, vote): p} with truth 1 or -1, and each kind's share of
    real spans. Votes count as independent given the truth; an abstention (0) is a vote too. A labeler that votes alike
    on all spans of a kind tells nothing about them; where all do, the votes are taken at their face."""
    start = {(c, v): 0.3 if v == 0 else 0.55 if c == v else 0.15 for c in (1, -1) for v in (1, 0, -1)}
    theta, share = {}, {}
    for kind in {c["kind"] for c in counts}:
        own = [c for c in counts if c["kind"] == kind]
        tells = [x for x in LABELERS if len({c[x] for c in own}) > 1]
        theta[kind], share[kind] = {x: dict(start) if x in tells or not tells else dict.fromkeys(start, 1 / 3) for x in LABELERS}, 0.5
        for _ in range(rounds if tells else 0):
            post = [posterior(c, theta, share) for c in own]
            share[kind] = (1 + sum(c["n"] * p for c, p in zip(own, post, strict=True))) / (2 + sum(c["n"] for c in own))
            for x in tells:
                for truth in (1, -1):
                    weight = [c["n"] * (p if truth == 1 else 1 - p) for c, p in zip(own, post, strict=True)]
                    for v in (1, 0, -1):
                        # pseudo-counts hold to the start where a kind has few spans
                        theta[kind][x][truth, v] = (3 * start[truth, v] + sum(w for w, c in zip(weight, own, strict=True) if c[x] == v)) / (3 + sum(weight))
    return theta, share


def posterior(votes: dict, theta: dict, share: dict) -> float:
    kind = votes["kind"]
    logit = math.log(share[kind] / (1 - share[kind])) + sum(math.log(theta[kind][x][1, votes[x]] / theta[kind][x][-1, votes[x]]) for x in LABELERS)
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, logit))))


def fit(counts: list[dict], rounds: int = 300, rate: float = 0.8, ridge: float = 1e-3) -> dict[str, list[float]]:
    """Logistic regression of the posteriors on the votes, for each kind, by gradient steps over the counted patterns:
    a constant and a weight for each labeler."""
    theta, share = reliabilities(counts)
    out = {}
    for kind in share:
        rows = [([1.0, *(float(c[x]) for x in LABELERS)], posterior(c, theta, share), float(c["n"])) for c in counts if c["kind"] == kind]
        total, w = sum(n for *_, n in rows), [0.0] * (1 + len(LABELERS))
        for _ in range(rounds):
            g = [ridge * a for a in w]
            for x, p, n in rows:
                miss = 1 / (1 + math.exp(-max(-30.0, min(30.0, sum(a * b for a, b in zip(w, x, strict=True)))))) - p
                g = [a + n / total * miss * b for a, b in zip(g, x, strict=True)]
            w = [a - rate * b for a, b in zip(w, g, strict=True)]
        out[kind] = w
    return out


def pattern_counts(proposed: DataFrame) -> list[dict]:
    """How often each pattern of votes occurs: at most kinds x 3^labelers rows, whatever the corpus holds."""
    one = proposed.select(F.inline("_spans"))
    return [r.asDict() for r in one.groupBy("kind", *LABELERS).agg(F.count(F.lit(1)).alias("n")).orderBy("kind", *LABELERS).collect()]


def score(s: Column, weights: dict[str, list[float]]) -> Column:
    """The classifier's probability that a span is real; a kind it was not fitted on has 0.5."""
    out = F.lit(0.0)
    for kind, (constant, *w) in sorted(weights.items()):
        out = F.when(s["kind"] == kind, reduce(Column.__add__, [s[x] * F.lit(a) for x, a in zip(LABELERS, w, strict=True)], F.lit(constant))).otherwise(out)
    return 1 / (1 + F.exp(-out))


def detect(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row for each document: key, counts and digest of the base spans, and all spans."""
    # only spans and votes are kept, not texts; the classifier and the result both read them
    proposed = stored(propose(docs.select(key, text), text).select(key, "_spans"), "pii")
    weights = fit(pattern_counts(proposed))
    base = F.filter("_spans", lambda s: s["rank"] < len(KINDS))
    overlaps = lambda s: F.exists(F.filter("_spans", lambda b: b["rank"] < len(KINDS)), lambda b: (b["start"] < s["end"]) & (s["start"] < b["end"]))
    more = F.filter("_spans", lambda s: (s["rank"] >= len(KINDS)) & (score(s, weights) >= 0.5) & ~overlaps(s))
    count = lambda k: F.size(F.filter("_spans", lambda s: s["kind"] == k)).cast("long")
    return proposed.select(
        key, *(count(k).alias(f"n_{k}") for k in KINDS), F.sha2(S.rendered(base).cast("binary"), 256).alias("base_sha256"),
        S.rendered(F.concat(base, more)).alias("spans"), F.size(more).cast("long").alias("n_added"),
    )


def redact(docs: DataFrame, found: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Texts with every span of found replaced by its kind in brackets, from the last span to the first."""
    by_end = F.reverse(F.split("spans", ","))
    cut = F.aggregate(by_end, F.coalesce(F.col(text), F.lit("")), lambda t, s: F.when(s == "", t).otherwise(F.concat(
        F.substr(t, F.lit(1), F.get(F.split(s, ":"), F.lit(1)).cast("int")), F.lit("["), F.get(F.split(s, ":"), F.lit(0)), F.lit("]"),
        F.substr(t, F.get(F.split(s, ":"), F.lit(2)).cast("int") + 1, F.char_length(t)))))
    return docs.join(found.select(key, "spans"), key, "left").withColumn(text, cut).drop("spans")
