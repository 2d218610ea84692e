"""Personal data by weak supervision, in DataFrame functions only.

Fixed patterns find the base spans (email, ip, card, phone), which always stay. Looser patterns find further candidates
(obfuscated mail addresses, phone numbers without a country code, card-like runs, secrets). Five labelers vote on each
candidate: strict pattern, checksum or shape, trigger words on its left, boundaries, and a gazetteer of things that only
look like it. Votes of the whole corpus are counted by pattern; a pattern is a kind and five votes, so at most
5 * 3^5 rows reach the driver. Expectation-maximisation there estimates how reliable each labeler is and how likely each
pattern is to be personal data, and a logistic span classifier is fitted to these likelihoods. Candidates that it accepts
and that overlap no base span are added.

Positions are code points, ends exclusive. Matches come from the split of the text at the pattern: the lengths of the
pieces between and of the matches give the places.

Results for odd input: a null or empty text has no spans and comes back empty; with no candidates in the corpus nothing is added; texts of any
length are scanned whole (patterns are written with possessive runs and left guards, so no run is scanned twice);
repeated rows give repeated rows; ``find`` keeps extra columns, and its outputs replace columns of the same name.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, let

#: Base kinds in the order in which spans are listed, then those that only the method adds to.
BASE_KINDS = ("email", "ip", "card", "phone")
ADDED_KINDS = ("secret",)

# The base patterns, as the contract words them. Runs are possessive where nothing that follows could need
# them back; the guard before a run starts a match where a run starts or right after the last match, as a scan from the
# left would.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?:(?<![0-9])|\G)[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
LOOSE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++\x20?[\[(]at[\])]\x20?[A-Za-z0-9-]++(?:\x20?(?:[\[(]dot[\])]|\.)\x20?[A-Za-z0-9-]++)++",
    "card": PATTERNS["card"],
    "phone": r"(?<![0-9+])\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}(?![0-9])",
    "secret": r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{16,}+=*",
}
#: What must be in a text for a pattern to be tried at all.
NEEDS = {"email": "text like '%@%'", "ip": "digit", "card": "digit", "phone": "text like '%+%'"}
LOOSE_NEEDS = {"email": "text rlike '[\\\\[(]at[\\\\])]'", "card": "digit", "phone": "digit", "secret": "digit"}

# Trigger words and look-alikes of the labelers.
TRIGGERS = {
    "email": r"(?i)(mail|contact|write to|reach)\W{0,8}$",
    "ip": r"(?i)(\bip|host|addr|server)\w*\W{0,8}$",
    "card": r"(?i)(card|visa|credit|payment)\w*\W{0,8}$",
    "phone": r"(?i)(phone|tel|call|fax|mobile|cell)\w*\W{0,8}$",
    "secret": r"(?i)(token|secret|passw\w*|api.?key|\bkey|auth\w*|bearer)\W{0,8}$",
}
LOOKALIKES = r"(?i)(isbn|version|page|vol|fig|row|order|item|sha\d*|md5|commit|rev)\W{0,4}$"
DOMAINS = ("com", "org", "net", "edu", "gov", "io", "info", "de", "fr", "es", "uk", "eu")
LABELERS = ("strict", "checksum", "trigger", "boundary", "lookalike")


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(m: Column) -> Column:
    """Whether the digits of a match pass the Luhn test."""

    def total(d):
        value = lambda i: F.substring(d, i, 1).cast("int") * F.when(F.pmod(F.length(d) - i, F.lit(2)) == 1, 2).otherwise(1)
        return F.aggregate(F.sequence(F.lit(1), F.length(d)), F.lit(0), lambda s, i: s + value(i) - F.when(value(i) > 9, 9).otherwise(0))

    return F.pmod(let(_digits(m), total), F.lit(10)) == 0


def _octets(m: Column) -> Column:
    small = lambda p: F.length(F.regexp_replace(p, "^0+", "")) <= 3
    return F.forall(F.split(m, r"\."), lambda p: small(p) & (F.coalesce(F.substring(F.regexp_replace(p, "^0+", ""), 1, 3).try_cast("int"), F.lit(0)) <= 255))


def passes(kind: str, m: Column) -> Column:
    """The base test that a match of a kind has to pass."""
    n = F.length(_digits(m))
    return {"email": F.lit(True), "ip": _octets(m), "card": n.between(13, 19) & F.when(n.between(13, 19), _luhn(m)).otherwise(False), "phone": n.between(9, 15)}[kind]


def _sums(lengths: Column) -> Column:
    """Running sums of an array in log2 passes, each linear."""
    rounds = F.when(F.size(lengths) > 1, F.ceil(F.log2(F.size(lengths))).cast("int")).otherwise(0)
    step = lambda acc, j: F.transform(acc, lambda x, i: x + F.when(i >= j, F.get(acc, i - j)).otherwise(0))
    powers = F.transform(F.when(rounds > 0, F.sequence(F.lit(0), rounds - 1)).otherwise(F.array().cast("array<int>")), lambda r: F.pow(F.lit(2.0), r).cast("int"))
    return F.aggregate(powers, lengths, step)


def matches(text: Column, pattern: str) -> Column:
    """array<struct<s int, e int, m string>>: leftmost non-overlapping matches with code point places."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    between = F.split(text, pattern)

    def placed(both):
        m, gaps = both["m"], both["g"]
        steps = F.transform(m, lambda x, i: F.length(F.get(gaps, i)) + F.length(x))
        return let(_sums(steps), lambda ends: F.transform(m, lambda x, i: F.struct((F.get(ends, i) - F.length(x)).alias("s"), F.get(ends, i).alias("e"), x.alias("m"))))

    none = F.array().cast("array<struct<s:int,e:int,m:string>>")
    return let(F.struct(found.alias("m"), between.alias("g")), lambda b: F.when(F.size(b["m"]) > 0, placed(b)).otherwise(none))


def _base_test(kind: str):
    return lambda x: passes(kind, x["m"])


def _span(number: int, voted: str | None = None):
    """A lambda from a match to its span, with the code of its votes for a candidate of the kind ``voted``."""
    plain = lambda x: [F.lit(number).alias("k"), x["s"].alias("s"), x["e"].alias("e")]
    return lambda x: F.struct(*plain(x), *([F.concat(F.lit(f"{voted}|"), _votes(voted, x)).alias("code")] if voted else []))


def _guarded(pattern: str, need: str) -> Column:
    none = F.array().cast("array<struct<s:int,e:int,m:string>>")
    return F.when(F.col("digit") if need == "digit" else F.expr(need), matches(F.col("text"), pattern)).otherwise(none)


def _votes(kind: str, x: Column) -> Column:
    """The five votes of a candidate (struct s, e, m) as characters +, - and 0."""
    m, n = x["m"], F.length(_digits(x["m"]))
    left = F.substring(F.col("text"), F.greatest(x["s"] - 23, F.lit(1)), F.least(x["s"], F.lit(24)))
    mark = lambda yes, no=None: F.when(yes, "+").when(no if no is not None else F.lit(False), "-").otherwise("0")
    beside = F.when(x["s"] > 0, F.substring(F.col("text"), x["s"], 1)).otherwise("").rlike(r"[\p{L}\p{N}]") | F.substring(F.col("text"), x["e"] + 1, 1).rlike(r"[\p{L}\p{N}]")
    domain = F.lower(F.regexp_extract(m, r"([A-Za-z]+)$", 1)).isin(*DOMAINS)
    strict = {"email": m.contains("@"), "card": n.between(15, 16) & m.rlike("^[3-6]"), "phone": m.rlike(r"^\(?[0-9]{3}\)?[\x20.-]") | m.startswith("+"), "secret": m.rlike("^[0-9a-f]{32,}$") | (m.rlike("[a-z]") & m.rlike("[A-Z]") & m.rlike("[0-9]"))}
    varied = F.size(F.array_distinct(F.split(m, ""))) >= 9
    checked = {"email": (domain, ~domain), "card": (F.when(n.between(13, 19), _luhn(m)).otherwise(False), ~F.when(n.between(13, 19), _luhn(m)).otherwise(False)), "phone": (n.between(10, 15), ~n.between(10, 15)), "secret": (varied & m.rlike("[0-9]") & m.rlike("[A-Za-z]"), ~(varied & m.rlike("[0-9]") & m.rlike("[A-Za-z]")))}
    return F.concat(mark(strict[kind]), mark(*checked[kind]), mark(left.rlike(TRIGGERS[kind])), mark(~beside, beside), F.when(left.rlike(LOOKALIKES), "-").otherwise("0"))


def candidates(docs: DataFrame) -> DataFrame:
    """``docs`` with ``base`` and ``more``: arrays of (k kind number, s, e) and of (k, s, e, code)."""
    order = {k: i for i, k in enumerate(BASE_KINDS + ADDED_KINDS)}
    docs = docs.withColumn("text", F.coalesce("text", F.lit(""))).withColumn("digit", F.col("text").rlike("[0-9]"))
    base = []
    for kind in BASE_KINDS:
        kept = F.filter(_guarded(PATTERNS[kind], NEEDS[kind]), _base_test(kind))
        base.append(F.transform(kept, _span(order[kind])))
    docs = docs.withColumn("base", F.concat(*base))
    more = []
    for kind in LOOSE:
        apart = F.filter(_guarded(LOOSE[kind], LOOSE_NEEDS[kind]), lambda x: ~F.exists("base", lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"])))
        if kind == "card":
            apart = F.filter(apart, lambda x: F.length(_digits(x["m"])) >= 13)
        more.append(F.transform(apart, _span(order[kind], kind)))
    return docs.withColumn("more", F.concat(*more)).drop("digit")


def estimate(counts: dict[str, int], rounds: int = 40) -> dict[str, float]:
    """Expectation-maximisation over vote patterns: the likelihood of each pattern to be personal data.

    Labelers are independent given the class and may abstain; their tables are shared by all kinds, the share of true
    candidates is per kind. Counts are smoothed by one. The start is the sign of the votes' sum.
    """
    votes = {c: [{"+": 1, "-": -1}.get(v, 0) for v in c.split("|")[1]] for c in counts}
    p = {c: 1 / (1 + math.exp(-sum(v))) for c, v in votes.items()}
    for _ in range(rounds):
        share, table = {}, {}
        for kind in {c.split("|")[0] for c in counts}:
            own = [c for c in counts if c.split("|")[0] == kind]
            share[kind] = (1 + sum(counts[c] * p[c] for c in own)) / (2 + sum(counts[c] for c in own))
        for i in range(len(LABELERS)):
            for y in (0, 1):
                weight = {v: 1.0 + 2.0 * (v == (1 if y else -1)) for v in (-1, 0, 1)}
                for c, n in counts.items():
                    weight[votes[c][i]] += n * (p[c] if y else 1 - p[c])
                table[i, y] = {v: w / sum(weight.values()) for v, w in weight.items()}
        for c in counts:
            s = share[c.split("|")[0]]
            odds = math.log(s / (1 - s)) + sum(math.log(table[i, 1][v] / table[i, 0][v]) for i, v in enumerate(votes[c]))
            p[c] = 1 / (1 + math.exp(-max(-30.0, min(30.0, odds))))
    return p


def classifier(counts: dict[str, int], p: dict[str, float], rounds: int = 300, rate: float = 0.5) -> dict[str, float]:
    """A logistic span classifier on kind and votes, fitted to the estimated likelihoods: its score of each pattern."""

    def features(c):
        kind, votes = c.split("|")
        return ["bias", f"kind={kind}", *(f"{name}{v}" for name, v in zip(LABELERS, votes, strict=True))]

    weight: dict[str, float] = {}
    total = max(1, sum(counts.values()))
    score = lambda c: 1 / (1 + math.exp(-sum(weight.get(f, 0.0) for f in features(c))))
    for _ in range(rounds):
        slope: dict[str, float] = {}
        for c, n in counts.items():
            error = n / total * (p[c] - score(c))
            for f in features(c):
                slope[f] = slope.get(f, 0.0) + error
        for f, g in slope.items():
            weight[f] = weight.get(f, 0.0) * (1 - 1e-4) + rate * g
    return {c: score(c) for c in counts}


def find(docs: DataFrame, threshold: float = 0.5, keep_text: bool = True) -> DataFrame:
    """``docs`` with ``base`` and ``spans``: arrays of (k, s, e), where k indexes BASE_KINDS + ADDED_KINDS.

    ``spans`` holds the base spans and those added, by kind, then start. Without the text, the candidates of the first
    pass are kept for the second; with it they are found again, which is cheaper than to store all texts.
    """
    order = [c for c in docs.columns if c not in ("base", "spans")]
    others = [c for c in order if c != "text"]
    # the caller's columns travel apart, so that no name of theirs meets one that is used here
    found = candidates(docs.select("text", *([F.struct(*others).alias("carried")] if others else [])))
    found = found if keep_text else cut(found.drop("text"))
    rows = found.select(F.explode("more.code").alias("code")).groupBy("code").count().collect()  # bounded by the number of vote patterns
    counts = {r["code"]: r["count"] for r in rows}
    scores = classifier(counts, estimate(counts)) if counts else {}
    accepted = sorted(c for c, s in scores.items() if s >= threshold)
    added = F.transform(F.filter("more", lambda x: x["code"].isin(accepted or ["-"])), lambda x: F.struct(x["k"].alias("k"), x["s"].alias("s"), x["e"].alias("e")))
    back = [F.col("text") if c == "text" else F.col("carried").getField(c).alias(c) for c in order if keep_text or c != "text"]
    return found.select(*back, F.array_sort("base").alias("base"), F.array_sort(F.concat("base", added)).alias("spans"))


def listed(spans: str) -> Column:
    """kind:start:end of each span, comma-joined."""
    names = F.array(*[F.lit(k) for k in BASE_KINDS + ADDED_KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def report(found: DataFrame) -> DataFrame:
    """The contract's columns."""
    count = lambda i: F.size(F.filter("base", lambda x: x["k"] == i)).cast("long")
    return found.select("doc_id", *[count(i).alias(f"n_{k}") for i, k in enumerate(BASE_KINDS)], F.sha2(listed("base").cast("binary"), 256).alias("base_sha256"), listed("spans").alias("spans"))


def redact(found: DataFrame) -> DataFrame:
    """The rows of ``find`` with every span in ``text`` replaced by its kind in angle brackets; spans that overlap share one."""
    names = F.array(*[F.lit(f"<{k.upper()}>") for k in BASE_KINDS + ADDED_KINDS])
    ordered = F.array_sort(F.transform("spans", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k"))))
    # furthest end so far, in log2 passes
    rounds = F.when(F.size("spans") > 1, F.ceil(F.log2(F.size("spans"))).cast("int")).otherwise(0)
    powers = F.transform(F.when(rounds > 0, F.sequence(F.lit(0), rounds - 1)).otherwise(F.array().cast("array<int>")), lambda r: F.pow(F.lit(2.0), r).cast("int"))
    reach = lambda o: F.aggregate(powers, F.transform(o, lambda x: x["e"]), lambda acc, j: F.transform(acc, lambda x, i: F.when(i >= j, F.greatest(x, F.get(acc, i - j))).otherwise(x)))

    def rebuilt(b):
        o, ends = b["o"], b["ends"]
        before = lambda i: F.when(i > 0, F.get(ends, i - 1)).otherwise(0)
        piece = lambda x, i: F.when(x["s"] >= before(i), F.concat(F.substring(F.col("text"), before(i) + 1, x["s"] - before(i)), F.get(names, x["k"]))).otherwise("")
        return F.concat(F.array_join(F.transform(o, piece), ""), F.substring(F.col("text"), F.element_at(ends, -1) + 1, F.length("text")))

    text = let(ordered, lambda o: let(F.struct(o.alias("o"), reach(o).alias("ends")), rebuilt))
    return found.withColumn("text", F.when(F.size("spans") > 0, text).otherwise(F.col("text")))
