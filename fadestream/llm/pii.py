r"""Personal data by candidate gradient boosting, scored in DataFrame expressions only.

Base kinds (email, ip, card, phone) are patterns with checks; their spans always stay. High-recall generators propose more
spans, which may overlap: keys and tokens, identity numbers, account numbers, spelt-out addresses of mail, national phone
numbers, card-length numbers (the base pattern drops a card that stands beside another number). Boosted trees judge each from its format and the words before it, and a calibrated probability decides. The trees
are trained once in a process on generated candidates (seeded; numpy on the driver) and become CASE expressions; texts
never leave the JVM. Positions count code points.

Work is linear in a text. A pattern whose match can begin anywhere in a run of characters is tried only where the run or the
last match ends before it, which gives the same leftmost matches; positions are running sums taken in blocks of matches, so no
list is copied once a match; a candidate's context comes from the pieces between matches, not from a search through the text.

Results for odd input: null counts as empty; no spans give the digest of the empty string; overlapping spans of different
kinds are all listed; repeated rows are answered row by row; very long texts are scanned whole; repeats of patterns are
possessive where nothing can be given back, so long runs of digits need no deep stack; an empty table gives no rows; other
columns are not read.
"""

from __future__ import annotations

import functools
import random
import re

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .boosting import Boosted, boost
from .common import text_of

# The base patterns, in order of the kinds.
BASE = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Generators of further candidates, wide on purpose.
MORE = {
    "secret": r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_-]{16,}+={0,2}",
    "national_id": r"(?<![0-9-])[0-9]{3}[ -][0-9]{2}[ -][0-9]{4}(?![0-9-])",
    "account": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "spelt_email": r"(?<![A-Za-z0-9._-])[A-Za-z0-9._-]++ ?(?:\(at\)|\[at\]|\{at\}| at ) ?[A-Za-z0-9-]++ ?(?:\(dot\)|\[dot\]|\{dot\}| dot ) ?[A-Za-z]{2,}",
    "number": r"(?<![A-Za-z0-9])(?:[0-9]{13,19}|[0-9]{4}(?:[ -][0-9]{4}){3})(?![A-Za-z0-9])",
    "local_phone": r"(?<![0-9+.-])\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4}(?![0-9.-])",
}
KINDS = [*BASE, *MORE]
#: Characters before a candidate that its features see; words that speak for and against. Matches in a block of running sums.
BEFORE, BLOCK = 32, 128
FOR = r"(?i)(?:token|secret|key|passw|pwd|auth|bearer|credential|ssn|social|security|iban|account|acct|phone|tel|call|mobile|fax|mail|contact|write)"
AGAINST = r"(?i)(?:order|invoice|version|commit|sha|hash|checksum|ref|part|model|isbn|build|page|room|sku|id)"
#: How keys of widely used services begin.
ISSUED = r"^(?:AKIA|ASIA|AIza|gh[oprsu]_|glpat-|sk[-_]|xox[abp]-|eyJ)"
FEATURES = ("kind", "length", "digits", "upper", "lower", "marks", "hex", "for", "against", "assigned", "lead_zero", "runs", "issued", "luhn")
#: Calibrated probability from which a proposed span is redacted.
CUT = 0.9


def _hits(text: Column, pattern: str, guard: Column | None = None) -> Column:
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    return hits if guard is None else F.when(guard, hits).otherwise(F.array().cast("array<string>"))


def _pairs(text: Column, pattern: str, hits: Column) -> Column:
    """Matches, leftmost and not overlapping, as structs: matched text t, length g of the gap before it, end r of that gap."""
    gaps = F.split(text, pattern, -1)
    empty = F.array().cast("array<struct<t:string,g:int,r:string>>")
    return F.when(
        F.size(hits) > 0,
        F.zip_with(hits, F.slice(gaps, 1, F.size(hits)), lambda h, g: F.struct(h.alias("t"), F.length(g).alias("g"), F.right(g, F.lit(BEFORE)).alias("r"))),
    ).otherwise(empty)


def _blocks(pairs: Column) -> Column:
    """Spans (s, e, both from the start of their block) by blocks: structs of the block's length n and its spans z."""
    empty = F.array().cast("array<struct<s:int,e:int>>")
    last = F.size(pairs) - 1

    def step(acc: Column, i: Column) -> Column:
        x = F.get(pairs, i)
        s = acc["n"] + x["g"]
        e = s + F.length(x["t"])
        return F.struct(e.alias("n"), F.concat(acc["z"], F.array(F.struct(s.alias("s"), e.alias("e")))).alias("z"))

    one = lambda lo: F.aggregate(F.sequence(lo, F.least(lo + (BLOCK - 1), last)), F.struct(F.lit(0).alias("n"), empty.alias("z")), step)
    return F.when(last >= 0, F.transform(F.sequence(F.lit(0), last, F.lit(BLOCK)), one)).otherwise(F.array().cast("array<struct<n:int,z:array<struct<s:int,e:int>>>>"))


def _placed(blocks: Column, good: Column, kind: str) -> Column:
    """Blocks with the places in the text (lo, hi) of their first and last span and those spans (s, e, k) that are good."""
    starts = F.aggregate(
        blocks, F.struct(F.lit(0).alias("at"), F.array().cast("array<int>").alias("out")), lambda a, b: F.struct((a["at"] + b["n"]).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")), lambda a: a["out"]
    )
    number = lambda i: F.get(good, i)

    def moved(b: Column, at: Column, first: Column) -> Column:
        kept = F.filter(F.transform(b["z"], lambda z, i: F.struct((z["s"] + at).alias("s"), (z["e"] + at).alias("e"), F.when(number(first + i), F.lit(KINDS.index(kind))).alias("k"))), lambda z: z["k"].isNotNull())
        return F.struct(at.alias("lo"), (at + b["n"]).alias("hi"), kept.alias("z"))

    numbered = F.transform(blocks, lambda b, j: F.struct(b.alias("b"), (j * BLOCK).alias("first")))
    return F.zip_with(numbered, starts, lambda x, at: moved(x["b"], at, x["first"]))


def _digits(t: Column) -> Column:
    return F.regexp_replace(t, "[^0-9]", "")


def _luhn(t: Column) -> Column:
    d = F.reverse(_digits(t))
    each = F.transform(F.sequence(F.lit(1), F.length(d)), lambda i: F.struct(i.alias("i"), F.ascii(F.substring(d, i, F.lit(1))).alias("c")))
    value = F.aggregate(each, F.lit(0), lambda a, x: a + F.when(x["i"] % 2 == 1, x["c"] - 48).otherwise((x["c"] - 48) * 2 - F.when(x["c"] > 52, 9).otherwise(0)))
    return value % 10 == 0


def _checked(kind: str, t: Column) -> Column:
    """Whether a match of a base pattern holds."""
    if kind == "ip":
        return F.forall(F.split(t, r"\."), lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.right(p, F.lit(3)).cast("int") <= 255))
    if kind == "card":
        return F.when(F.length(_digits(t)).between(12, 19), _luhn(t)).otherwise(F.lit(False))
    return F.length(_digits(t)).between(9, 15) if kind == "phone" else F.lit(True)


def _verified(kind: str, pairs: Column) -> Column:
    return F.transform(pairs, lambda x: _checked(kind, x["t"]))


def _count(t: Column, unwanted: str) -> Column:
    return F.length(F.regexp_replace(t, unwanted, "")).cast("double")


def _features(kind: str, t: Column, before: Column) -> list[Column]:
    return [
        F.lit(float(KINDS.index(kind))),
        F.length(t).cast("double"),
        _count(t, "[^0-9]"),
        _count(t, "[^A-Z]"),
        _count(t, "[^a-z]"),
        _count(t, "[A-Za-z0-9]"),
        t.rlike("^[0-9a-fA-F]+$").cast("double"),
        before.rlike(FOR).cast("double"),
        before.rlike(AGAINST).cast("double"),
        before.rlike(r"[=:]\s*[\"']?$").cast("double"),
        t.startswith("0").cast("double"),
        F.size(F.regexp_extract_all(t, F.lit("[0-9]+"), F.lit(0))).cast("double"),
        t.rlike(ISSUED).cast("double"),
        _luhn(t).cast("double") if kind == "number" else F.lit(0.0),
    ]


def luhn_sum(digits: str) -> int:
    """The check sum of a number, last digit included; valid ones end in 0."""
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(digits)))


def features_of(kind: str, t: str, before: str) -> list[float]:
    """The same features in Python, for training."""
    return [
        float(KINDS.index(kind)),
        float(len(t)),
        float(len(re.sub("[^0-9]", "", t))),
        float(len(re.sub("[^A-Z]", "", t))),
        float(len(re.sub("[^a-z]", "", t))),
        float(len(re.sub("[A-Za-z0-9]", "", t))),
        float(bool(re.search("^[0-9a-fA-F]+$", t))),
        float(bool(re.search(FOR, before))),
        float(bool(re.search(AGAINST, before))),
        float(bool(re.search(r"[=:]\s*[\"']?$", before))),
        float(t.startswith("0")),
        float(len(re.findall("[0-9]+", t))),
        float(bool(re.search(ISSUED, t))),
        float(kind == "number" and luhn_sum(re.sub("[^0-9]", "", t)) % 10 == 0),
    ]


def labelled_candidates(n: int, seed: int) -> tuple[np.ndarray, np.ndarray]:
    """Generated candidates with contexts: personal ones, and look-alikes (codes, words, dates, sums of parts)."""
    rng = random.Random(seed)
    pick = rng.choice

    def some(alphabet: str, a: int, b: int) -> str:
        return "".join(rng.choices(alphabet, k=rng.randint(a, b)))

    word = lambda: some("abcdefghijklmnoprstuvw", 2, 9)
    low, hexa, mix = "abcdefghijklmnopqrstuvwxyz", "0123456789abcdef", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"
    plain = lambda: f"{word()} {word()} {word()} "
    rows, y = [], []

    def put(kind: str, t: str, before: str, good: bool) -> None:
        rows.append(features_of(kind, t, before[-BEFORE:]))
        y.append(float(good))

    for _ in range(n):
        kind, good = pick(list(MORE)), rng.random() < 0.5
        if kind == "secret":
            naming = pick(["token", "secret", "api_key", "password", "access key", "auth", "key"])
            if good:
                issued = lambda: pick([
                    lambda: pick(["AKIA", "ASIA"]) + some("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 16, 16), lambda: pick(["ghp_", "gho_"]) + some(mix, 36, 36),
                    lambda: pick(["sk-", "sk_live_"]) + some(mix, 24, 48), lambda: "xoxb-" + some("0123456789", 10, 12) + "-" + some(mix, 24, 24), lambda: "AIza" + some(mix + "_-", 35, 35),
                ])()
                if rng.random() < 0.3:
                    put(kind, issued(), plain(), True)
                    continue
                t = pick([issued, lambda: some(hexa, 32, 64), lambda: some(mix, 20, 48), lambda: "AK" + some("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 16, 18), lambda: "sk_" + some(mix, 24, 40)])()
                put(kind, t, plain() + naming + pick([" = ", "=", ": ", ' = "', '="', " "]) + "", True)
            else:
                t = pick([lambda: some(low, 16, 40), lambda: some("0123456789", 16, 24), lambda: "-".join(word() for _ in range(4)), lambda: "/".join(word() for _ in range(4)), lambda: some(hexa, 32, 40), lambda: some(low, 16, 24).upper(), lambda: some("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 16, 24)])()
                put(kind, t, plain() + (pick(["commit ", "sha ", "hash: ", "checksum = "]) if set(t) <= set(hexa) and any(c.isdigit() for c in t) else pick(["", "", "sku "]) if t.isupper() and not t.isalpha() else pick(["", "", naming + " "])), False)
        elif kind == "national_id":
            t = pick(["-", "-", " "]).join([some("0123456789", 3, 3), some("0123456789", 2, 2), some("0123456789", 4, 4)])
            put(kind, t, plain() + (pick(["ssn ", "SSN: ", "social security number ", "security no. "]) if good else pick(["part ", "order ", "ref ", "", "model "])), good)
        elif kind == "account":
            body = some("0123456789", 14, 22) if good else some("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 14, 22)
            t = some("ABCDEFGHIJ", 2, 2) + some("0123456789", 2, 2) + (body if rng.random() < 0.5 else " ".join(body[i : i + 4] for i in range(0, len(body), 4)))
            put(kind, t, plain() + (pick(["IBAN ", "iban: ", "account ", "acct "]) if good else pick(["sku ", "part ", "", "build "])), good)
        elif kind == "number":
            t = pick("23456" if good else "0123456789") + some("0123456789", 11, 17)
            right = -luhn_sum(t + "0") % 10
            t += str(right if good else (right + rng.randint(1, 9)) % 10)
            if len(t) == 16 and rng.random() < 0.5:
                t = pick([" ", "-"]).join(t[i : i + 4] for i in range(0, 16, 4))
            put(kind, t, plain() + pick(["", "card ", some("0123456789", 12, 16) + " "]), good)
        elif kind == "spelt_email":
            wrap = good or rng.random() < 0.1
            a, d = pick([(" (at) ", " (dot) "), (" [at] ", " [dot] "), ("(at)", "(dot)"), ("[at]", "[dot]")]) if wrap else (" at ", " dot ")
            t = f"{word()}{pick(['.', '_', '']) if wrap else ''}{word()}{a}{word()}{d}{pick(['com', 'org', 'net']) if wrap else word()}"
            put(kind, t, plain() + (pick(["mail ", "contact ", "write to ", ""]) if good else ""), good)
        else:
            t = pick(["{}-{}-{}", "({}) {}-{}", "{}.{}.{}", "{} {} {}"]).format(some("23456789", 3, 3), some("0123456789", 3, 3), some("0123456789", 4, 4))
            put(kind, t, plain() + (pick(["phone ", "tel. ", "call ", "mobile: ", "fax "]) if good else pick(["order ", "ref ", "", "part ", "invoice "])), good)
    return np.array(rows), np.array(y)


@functools.cache
def trained(n: int = 6000, seed: int = 23) -> Boosted:
    return boost(*labelled_candidates(n, seed))


def _accepted(kind: str, pairs: Column, model: Boosted) -> Column:
    """For each match of a generator, whether its calibrated probability reaches the cut. No match is shorter than eleven characters, so three pieces hold its context."""
    least = F.lit(model.margin_for(CUT))

    def piece(i: Column) -> Column:
        return F.coalesce(F.concat(F.get(pairs, i)["r"], F.right(F.get(pairs, i)["t"], F.lit(BEFORE))), F.lit(""))

    def judged(x: Column, i: Column) -> Column:
        before = F.right(F.concat(*(piece(i - j) for j in (3, 2, 1)), x["r"]), F.lit(BEFORE))
        made = F.transform(F.array(before), lambda b: F.array(*_features(kind, x["t"], b)))
        return F.get(F.transform(made, lambda f: model.expression(lambda j: f[j], lambda c, a, b: F.when(c, a).otherwise(b), F.lit)), F.lit(0)) >= least

    return F.transform(pairs, judged)


def _listed(spans: Column) -> Column:
    name = F.array(*(F.lit(k) for k in KINDS))
    order = F.array_sort(F.transform(spans, lambda z: F.struct(z["s"].alias("s"), z["k"].alias("k"), z["e"].alias("e"))))
    return F.array_join(F.transform(order, lambda z: F.concat_ws(":", F.get(name, z["k"]), z["s"].cast("string"), z["e"].cast("string"))), ",")


def personal_data(docs: DataFrame, model: Boosted | None = None) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_spans (long, base and added ones): a row per input row."""
    model = model or trained()
    text = F.col("text")
    guards = {"email": F.contains(text, F.lit("@")), "ip": text.rlike(r"[0-9]\.[0-9]"), "phone": F.contains(text, F.lit("+")), "spelt_email": text.rlike(r"(?:\(|\[|\{| )dot(?:\)|\]|\}| )"), "account": text.rlike("[A-Z]{2}[0-9]{2}")}
    kinds, patterns = list(KINDS), BASE | MORE
    out = docs.select("doc_id", text_of().alias("text"))
    # one step a projection: each column is read more than once by the next, so none is computed again
    out = out.select("doc_id", "text", *(_hits(text, patterns[k], guards.get(k)).alias(f"hits_{k}") for k in kinds))
    out = out.select("doc_id", *(_pairs(text, patterns[k], F.col(f"hits_{k}")).alias(f"pairs_{k}") for k in kinds))
    good = {k: _verified(k, F.col(f"pairs_{k}")) if k in BASE else _accepted(k, F.col(f"pairs_{k}"), model) for k in kinds}
    out = out.select("doc_id", *(_blocks(F.col(f"pairs_{k}")).alias(f"blocks_{k}") for k in kinds), *(good[k].alias(f"good_{k}") for k in kinds))
    out = out.select("doc_id", *(_placed(F.col(f"blocks_{k}"), F.col(f"good_{k}"), k).alias(k) for k in kinds))
    spans = lambda k: F.flatten(F.transform(k, lambda b: b["z"]))
    base = F.concat(*(F.col(k) for k in BASE))
    out = out.select("doc_id", *(spans(k).alias(f"n_{k}") for k in BASE), base.alias("near"), F.concat(*(spans(k) for k in MORE)).alias("more"))
    touches = lambda z: F.exists("near", lambda b: (b["lo"] < z["e"]) & (z["s"] < b["hi"]) & F.exists(b["z"], lambda y: (y["s"] < z["e"]) & (z["s"] < y["e"])))
    out = out.select("doc_id", *(F.size(f"n_{k}").cast("long").alias(f"n_{k}") for k in BASE), F.concat(*(F.col(f"n_{k}") for k in BASE)).alias("base"), F.filter("more", lambda z: ~touches(z)).alias("more"))
    return out.select("doc_id", *(f"n_{k}" for k in BASE), F.sha2(_listed(F.col("base")), 256).alias("base_sha256"), _listed(F.concat("base", "more")).alias("spans"), F.size(F.concat("base", "more")).cast("long").alias("n_spans"))
