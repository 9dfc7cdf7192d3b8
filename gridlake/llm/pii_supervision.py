"""Personal data by weak supervision, in DataFrame functions only.

Candidates are what the base patterns match, also where the base rule's test drops it, and
what looser patterns of the same four kinds match.  Labelers vote on each of them: a strict
test, a gazetteer, the words before it and its shape.  Expectation-maximisation over the
counts of vote patterns (a bounded table) estimates how reliable each labeler is; its
posteriors train a naive Bayes span classifier over votes and features of the span, which
decides every candidate that is no base match.  Base matches always stay; a span that is
added overlaps none of them.

Defined results: a null text is empty and has no spans; positions are code points, end
exclusive; rows are judged one by one, so repeated rows and nulls in other columns need no
care, and columns of any other name are kept by ``redacted`` and not read by ``report``; an
empty table gives no rows; a kind without candidates has no model and adds none.  Texts of
any length are scanned whole: no pattern repeats a group in a way that the engine answers
by recursion or retries, and lists of matches are gone through in runs of the square root
of their number, so the work on one text grows little more than its length.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from gridlake.llm.common import Scratch

KINDS = ("email", "ip", "card", "phone")
# The base patterns.  Lookbehinds and possessive loops only keep a failing
# try from being repeated inside the same run; runs of digits outside 14 to 19 never match.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){13,18}(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
# Looser patterns, their candidates are decided by the classifier.
LOOSE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+(?:\x20?[\[(]at[\])]\x20?[A-Za-z0-9-]{1,63}+(?:(?:\x20?[\[(]dot[\])]\x20?|\x20dot\x20|\.)[A-Za-z0-9-]{1,63}+){1,4}|\x20at\x20[A-Za-z0-9-]{1,63}+(?:\x20dot\x20[A-Za-z0-9-]{1,63}+){1,4})",
    "ip": r"(?<![0-9.-])[0-9]{1,3}(?:(?:\x20?[\[(](?:\.|dot)[\])]\x20?[0-9]{1,3}){3}|(?:-[0-9]{1,3}){3})(?![0-9-])",
    "card": r"(?<![0-9._/])[0-9]{4}(?:(?:[._/]|\x20\x20|\x20-\x20)[0-9]{4}){3}(?![0-9])",
    "phone": r"(?<![0-9+.)(-])\(?[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]{4}(?![0-9-])",
}
# What a text with a match of the patterns above holds; quick to look for.
HINT = {
    "email": ("@", r"[\[(]at[\])]|\x20dot\x20"),
    "ip": (r"[0-9]\.[0-9]", r"[0-9](?:-[0-9]|\x20?[\[(])"),
    "card": (r"[0-9][0-9\x20-]{13}", r"[0-9]{4}[._/\x20]{1,2}[0-9-]"),
    "phone": (r"\+[0-9]", r"[0-9]{3}\)?[\x20.-][0-9]{3}[\x20.-][0-9]"),
}
# Gazetteers and words that announce a kind.
ENDINGS = ("com", "org", "net", "edu", "gov", "info", "io", "de", "fr", "es", "uk", "it", "nl", "eu")
CALLING = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "36", "39", "40", "41", "43", "44", "45", "46", "47", "48", "49", "52", "55", "61", "81", "82", "86", "91")
BEFORE = {
    "email": r"(?i)(?:mail|contact|write|correo|courriel|kontakt)[^\n]{0,24}$",
    "ip": r"(?i)(?:\bip\b|host|server|addr|client)[^\n]{0,24}$",
    "card": r"(?i)(?:card|visa|credit|pay|karte|tarjeta|carte)[^\n]{0,24}$",
    "phone": r"(?i)(?:phone|tel|call|fax|mobile|handy)[^\n]{0,24}$",
}
CONTEXT = 48
ROUNDS = 25
UNSURE = 0.1
#: Working columns beside those of the documents.
CANDIDATES, TAKEN = "__gridlake_candidates", "__gridlake_taken"

MATCH = "struct<start:int,stop:int,body:string,ahead:string,behind:string>"
CANDIDATE = "struct<start:int,stop:int,kind:int,base:boolean,strict:int,gazetteer:int,context:int,shape:int,length:int,before:string,after:string,reach:int,next:int>"
#: Larger than any position.
FAR = (1 << 31) - 1


def let(value: Column, then: Callable[[Column], Column]) -> Column:
    """``then(value)``, the value being worked out once."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def parts_of(xs: Column) -> Column:
    """A list that is not empty as runs of about the square root of its number."""
    size = F.ceil(F.sqrt(F.size(xs))).cast("int")
    return let(size, lambda c: F.transform(F.sequence(F.lit(0), F.ceil(F.size(xs) / c).cast("int") - 1), lambda k: F.slice(xs, k * c + 1, c)))


def scanned(xs: Column, zero: int, step: Callable, emit: Callable, kind: str) -> Column:
    """``emit(state, x)`` for every ``x`` of a list, the state being what ``step`` made of ``zero``
    over those before it.  Lists are only appended to inside a run, so a long one is cheap."""
    made = f"struct<state:int,out:array<{kind}>>"

    def one(acc: Column, x: Column) -> Column:
        return F.struct(step(acc["state"], x).cast("int").alias("state"), F.array_append(acc["out"], emit(acc["state"], x).cast(kind)).alias("out"))

    def run(done: Column, part: Column) -> Column:
        state = F.coalesce(F.get(done, F.size(done) - 1)["state"], F.lit(zero))
        return F.array_append(done, F.aggregate(part, F.struct(state.alias("state"), F.array().cast(f"array<{kind}>").alias("out")).cast(made), one))

    def all_runs(own: Column) -> Column:
        done = F.aggregate(parts_of(own), F.array().cast(f"array<{made}>"), run)
        return F.when(F.size(own) > 0, F.flatten(F.transform(done, lambda r: r["out"]))).otherwise(F.array().cast(f"array<{kind}>"))

    return let(xs, all_runs)


def placed(text: Column, pattern: str, hint: str) -> Column:
    """All matches with their positions, the text before them and the character behind,
    neither beyond a match next to them: the lengths of what lies between matches add up."""

    def joined(bodies: Column, between: Column) -> Column:
        n = F.size(bodies)
        both = F.arrays_zip(F.slice(between, 1, n).alias("gap"), bodies.alias("body"), F.slice(between, 2, n).alias("rest"))
        sized = F.transform(both, lambda x: F.struct(
            F.length(x["gap"]).alias("skip"), F.length(x["body"]).alias("size"), x["body"].alias("body"), F.right(x["gap"], F.lit(CONTEXT)).alias("ahead"), F.left(x["rest"], F.lit(1)).alias("behind"),
        ))
        return scanned(
            sized, 0, lambda at, x: at + x["skip"] + x["size"],
            lambda at, x: F.struct((at + x["skip"]).alias("start"), (at + x["skip"] + x["size"]).alias("stop"), x["body"].alias("body"), x["ahead"].alias("ahead"), x["behind"].alias("behind")), MATCH,
        )

    found = let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda bodies: let(F.split(text, pattern, -1), lambda between: joined(bodies, between)))
    return F.when(text.rlike(hint) & text.rlike(pattern), found).otherwise(F.array().cast(f"array<{MATCH}>"))


def digits(body: Column) -> Column:
    return F.regexp_replace(body, "[^0-9]", "")


def luhn(body: Column) -> Column:
    """Whether the digits pass the check sum."""
    back = F.reverse(digits(body))
    doubled = F.transform(F.sequence(F.lit(1), F.length(back)), lambda i: F.substring(back, i, F.lit(1)).cast("int") * (F.lit(2) - i % 2))
    return F.aggregate(doubled, F.lit(0), lambda a, d: a + F.when(d > 9, d - 9).otherwise(d)) % 10 == 0


def octets(body: Column) -> Column:
    """Whether every number is at most 255."""
    def small(part: Column) -> Column:
        value = F.regexp_replace(part, "^0+", "")
        return F.when(F.length(value) > 3, F.lit(False)).when(value == "", F.lit(True)).otherwise(F.when(F.length(value) <= 3, value).otherwise("0").cast("int") <= 255)

    return F.forall(F.regexp_extract_all(body, F.lit("[0-9]+"), F.lit(0)), small)


def valid(kind: str, body: Column) -> Column:
    """The base rule's test behind its pattern."""
    if kind == "ip":
        return octets(body)
    if kind == "card":
        return luhn(body)
    if kind == "phone":
        return F.length(digits(body)).between(10, 15)
    return F.lit(True)


def strict(kind: str, body: Column) -> Column:
    """The strict test of a loose candidate."""
    if kind == "email":
        return body.rlike(r"[\[(]at[\])]|\x20dot\x20") & body.rlike(r"[A-Za-z]{2,}$")
    if kind == "phone":
        return F.regexp_replace(body, "[^0-9]", "").rlike("^[2-9][0-9]{2}[2-9]")
    return valid(kind, body)


def gazetteer(kind: str, body: Column) -> Column:
    """1, 0 or -1 (no vote)."""
    if kind == "email":
        return F.lower(F.regexp_extract(body, r"([A-Za-z]++)$", 1)).isin(*ENDINGS).cast("int")
    if kind == "phone":
        code = digits(body)
        known = F.lit(False)
        for n in (1, 2):
            known |= F.substring(code, 1, n).isin(*[c for c in CALLING if len(c) == n])
        return F.when(body.startswith("+"), known.cast("int")).otherwise(-1)
    if kind == "card":
        return F.substring(digits(body), 1, 1).isin("3", "4", "5", "6").cast("int")
    return F.when(F.regexp_extract(body, r"^0*([0-9]{1,3})", 1).isin("10", "127", "172", "192"), F.lit(1)).otherwise(-1)


def shape(kind: str, body: Column) -> Column:
    n = F.length(body)
    low, high = {"email": (8, 60), "ip": (7, 31), "card": (14, 25), "phone": (10, 20)}[kind]
    return n.between(low, high).cast("int")


def candidates(text: Column) -> Column:
    """All candidates of a text with the labelers' votes and the classifier's features."""
    out = []
    for number, kind in enumerate(KINDS):
        out.append(F.transform(placed(text, BASE[kind], HINT[kind][0]), judged(kind, number, True)))
        out.append(F.transform(placed(text, LOOSE[kind], HINT[kind][1]), judged(kind, number, False)))
    return free(F.concat(*out).cast(f"array<{CANDIDATE}>"))


def judged(kind: str, number: int, base: bool) -> Callable[[Column], Column]:
    """What a match becomes: a candidate with its votes and features."""

    def candidate(x: Column) -> Column:
        body = x["body"]
        ok = valid(kind, body) if base else F.lit(False)
        return F.struct(
            x["start"].alias("start"), x["stop"].alias("stop"), F.lit(number).alias("kind"), ok.alias("base"),
            (ok if base else strict(kind, body)).cast("int").alias("strict"), gazetteer(kind, body).alias("gazetteer"),
            F.when(x["ahead"].rlike(BEFORE[kind]), 1).otherwise(-1).alias("context"), shape(kind, body).alias("shape"),
            F.least(F.lit(7), F.floor(F.length(body) / 4).cast("int")).alias("length"),
            sort_of(F.right(x["ahead"], F.lit(1))).alias("before"), sort_of(x["behind"]).alias("after"), F.lit(0).alias("reach"), F.lit(FAR).alias("next"),
        )

    return candidate


def sort_of(char: Column) -> Column:
    """The sort of a neighbouring character."""
    return F.when(char == "", "edge").when(char.rlike(r"\s"), "space").when(char.rlike("[0-9]"), "digit").when(char.rlike(r"\p{L}"), "letter").otherwise("other")


def estimate(patterns: list[tuple[tuple[int, ...], int]], sure: list[tuple[tuple[int, ...], int]] = (), rounds: int = ROUNDS) -> dict[tuple[int, ...], float]:
    """Posterior of each vote pattern by expectation-maximisation.

    Each labeler has a rate of voting yes on true and on false candidates; no vote says
    nothing.  ``sure`` are patterns of candidates known to be true: where they are voted on,
    they alone fix a labeler's rate on true candidates, so the others can't drag it to what
    they are.  These start from their share of yes votes, scaled down by UNSURE if some are sure.
    """
    doubt = UNSURE if sure else 1.0
    post = {v: doubt * (sum(x == 1 for x in v) + 0.5) / (sum(x >= 0 for x in v) + 1) for v, _ in patterns}
    known = sum(n for _, n in sure)
    for _ in range(rounds):
        true = sum(post[v] * n for v, n in patterns) + known + 1
        prior = true / (sum(n for _, n in patterns) + known + 2)
        rates = []
        for k in range(len((patterns or sure)[0][0])):
            rate = []
            for side in (True, False):
                weight = [(n, v[k]) for v, n in sure if v[k] >= 0 and side] or [((post[v] if side else 1 - post[v]) * n, v[k]) for v, n in patterns if v[k] >= 0]
                # a labeler is taken to be better than chance before anything is seen
                rate.append((sum(w for w, x in weight if x == 1) + (2 if side else 1)) / (sum(w for w, _ in weight) + 3))
            rates.append(rate)
        for v, _ in patterns:
            odds = math.log(prior / (1 - prior))
            for (yes, no), x in zip(rates, v, strict=True):
                if x >= 0:
                    odds += math.log(yes / no) if x == 1 else math.log((1 - yes) / (1 - no))
            post[v] = 1 / (1 + math.exp(-max(-500.0, min(500.0, odds))))
    return post


def fit(found: DataFrame) -> dict[tuple[int, str, str], float]:
    """Log odds of the span classifier, by kind, feature and value.

    ``found`` has ``kind`` and the votes and features of every candidate of all texts; two
    aggregates over it give tables whose sizes don't depend on the data's.
    """
    votes = ("strict", "gazetteer", "context", "shape")
    seen = found.groupBy("kind", "base", *votes).count().collect()
    posterior: dict[int, dict] = {}
    for kind in range(len(KINDS)):
        own, sure = ([(tuple(r[v] for v in votes), r["count"]) for r in seen if r.kind == kind and r.base == known] for known in (False, True))
        if own or sure:
            posterior[kind] = estimate(own, sure)
    if not posterior:
        return {}
    p = F.lit(0.5)
    for kind, table in posterior.items():
        for v, x in table.items():
            match = F.col("kind") == kind
            for name, value in zip(votes, v, strict=True):
                match &= F.col(name) == value
            p = F.when(match, F.lit(x)).otherwise(p)
    p = F.when(F.col("base"), F.lit(1.0)).otherwise(p)
    names = ("length", "before", "after", *votes)
    said = F.explode(F.array(*[F.struct(F.lit(n).alias("name"), F.col(n).cast("string").alias("value")) for n in names]))
    sums = found.select("kind", p.alias("p"), said.alias("f")).groupBy("kind", "f.name", "f.value").agg(F.sum("p").alias("yes"), F.sum(1 - F.col("p")).alias("no")).collect()
    model: dict[tuple[int, str, str], float] = {}
    for kind in posterior:
        yes = sum(r.yes for r in sums if r.kind == kind and r.name == "length")
        no = sum(r.no for r in sums if r.kind == kind and r.name == "length")
        model[kind, "", ""] = math.log((yes + 1) / (no + 1))
        for r in sums:
            if r.kind == kind:
                model[kind, r.name, r.value] = math.log((r.yes + 1) / (yes + 8)) - math.log((r.no + 1) / (no + 8))
    return model


def accepted(x: Column, model: dict[tuple[int, str, str], float]) -> Column:
    """Base matches, and other candidates that the classifier takes for true."""
    score = F.lit(0.0)
    for (kind, name, value), w in model.items():
        same = x["kind"] == kind
        if name:
            same &= x[name].cast("string") == value
        score += F.when(same, F.lit(w)).otherwise(0.0)
    known = x["kind"].isin(*sorted({k for k, _, _ in model})) if model else F.lit(False)
    return x["base"] | (known & (score > 0))


def free(spans: Column) -> Column:
    """Candidates by position: base matches, and others that overlap none of them."""

    def apart(own: Column) -> Column:
        ahead = scanned(own, 0, lambda at, x: F.when(x["base"], F.greatest(at, x["stop"])).otherwise(at), lambda at, x: x.withField("reach", at), CANDIDATE)
        back = scanned(F.reverse(ahead), FAR, lambda at, x: F.when(x["base"], F.least(at, x["start"])).otherwise(at), lambda at, x: x.withField("next", at), CANDIDATE)
        return F.filter(F.reverse(back), lambda x: x["base"] | ((x["reach"] <= x["start"]) & (x["next"] >= x["stop"])))

    def sorted_(own: Column) -> Column:
        return let(F.array_sort(own), lambda xs: F.when(F.exists(xs, lambda x: ~x["base"]), apart(xs)).otherwise(xs))

    return let(spans, lambda own: F.when(F.size(own) > 0, sorted_(own)).otherwise(own))


def ordered(spans: Column) -> Column:
    return F.array_sort(F.transform(spans, lambda x: F.struct(x["start"].alias("start"), x["kind"].alias("kind"), x["stop"].alias("stop"))))


def named(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["start"].cast("string"), x["stop"].cast("string"))), ",")


def with_candidates(docs: DataFrame) -> DataFrame:
    return docs.withColumn(CANDIDATES, candidates(F.coalesce(F.col("text").cast("string"), F.lit(""))))


def fit_table(table: DataFrame) -> dict[tuple[int, str, str], float]:
    return fit(table.where(F.size(CANDIDATES) > 0).select(F.explode(CANDIDATES).alias("c")).select("c.*"))


def report(s: Scratch, docs: DataFrame) -> DataFrame:
    """Counts, the base digest and all spans of every document."""
    plain = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    table = s.keep(with_candidates(plain).select("doc_id", CANDIDATES), "candidates")
    model = fit_table(table)
    taken = table.withColumn("taken", F.filter(CANDIDATES, lambda x: accepted(x, model)))
    taken = taken.select("doc_id", "taken", ordered(F.filter("taken", lambda x: x["base"])).alias("base"))
    numbers = F.transform("base", lambda x: x["kind"])
    counts = [(F.size(numbers) - F.size(F.array_remove(numbers, F.lit(n)))).cast("long").alias(f"n_{kind}") for n, kind in enumerate(KINDS)]
    return taken.select("doc_id", *counts, F.sha2(named(F.col("base")), 256).alias("base_sha256"), named(ordered(F.col("taken"))).alias("spans"))


def redacted(docs: DataFrame, model: dict[tuple[int, str, str], float]) -> DataFrame:
    """``docs`` (with CANDIDATES) with every accepted span of ``text`` replaced by its kind in
    brackets.  Spans that overlap are replaced together under the first one's kind.

    The text is cut into one piece for each run of spans before each span's own is cut out.
    """
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])
    text, piece = F.col("text").cast("string"), "struct<lo:int,hi:int,kind:int>"

    def rebuilt(spans: Column) -> Column:
        # the text kept before a span, none where an earlier span reaches over its start
        cuts = scanned(spans, 0, lambda at, x: F.greatest(at, x["stop"]), lambda at, x: F.struct(at.alias("lo"), x["start"].alias("hi"), x["kind"].alias("kind")), piece)
        return let(F.filter(cuts, lambda x: x["lo"] <= x["hi"]), lambda own: F.array_join(F.flatten(F.transform(parts_of(own), run)), ""))

    def run(part: Column) -> Column:
        lo, hi = F.get(part, F.lit(0))["lo"], F.get(part, F.size(part) - 1)["hi"]
        return let(F.substring(text, lo + 1, hi - lo), lambda body: F.transform(part, lambda x: F.concat(F.substring(body, x["lo"] - lo + 1, x["hi"] - x["lo"]), F.get(names, x["kind"]))))

    tail = F.array_max(F.transform(TAKEN, lambda x: x["stop"]))
    taken = docs.withColumn(TAKEN, ordered(F.filter(CANDIDATES, lambda x: accepted(x, model))))
    done = F.concat(rebuilt(F.col(TAKEN)), F.substring(text, tail + 1, F.length(text)))
    return taken.withColumn("text", F.when(F.size(TAKEN) > 0, done).otherwise(text)).drop(CANDIDATES, TAKEN)
