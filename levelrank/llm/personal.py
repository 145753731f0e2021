"""Personal data by weak supervision, in DataFrame operations only.

Candidates are the spans that the base patterns find (valid or not) and looser spans: spelled-out
addresses, card numbers next to other digits, phone numbers without a plus, long internet addresses. Three
labelers vote on each candidate: its form (the base check, or its like for looser spans), a gazetteer (endings
of domains, dialling codes, issuer digits, address ranges) and the words before it. Expectation-maximisation
over the counts of vote patterns estimates how reliable each labeler is for each kind and how likely
each pattern is a true span. These posteriors are the soft labels of the final span classifier, a
naive Bayes model over the span's shape, whose weights are aggregates over all candidates. Valid base
spans always stay; the classifier adds looser spans whose form is sound, and base matches that
fail their check only where the words before ask for one. Of looser spans that meet, the first stays.

Null and empty texts have no spans; repeated rows and rows without doc_id are reported one by one; a very
long text is one row whose candidates are rows of their own; other columns are not read.

Only counts per vote pattern and per shape feature, whose number is fixed, reach the driver.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelrank.plans.staging import materialise, small_rows

KINDS = ("email", "ip", "card", "phone")
#: The base patterns, written so that long runs cost linear time: a run is
#: entered at its start only and never given back.
NAME = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"[{NAME}](?:(?<![{NAME}]{{2}})|(?<=\G.))[{NAME}]*+@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"[0-9](?<![0-9]{2})[0-9]*+\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold before a pattern is tried.
SIGNS = {"email": "@", "ip": ".", "card": "", "phone": "+"}
#: Looser spans, each with what a text must hold before it is tried: addresses spelled out, card numbers whose
#: neighbours hide them from the base pattern, numbers in groups without a plus or after the exit code.
LOOSE = (
    ("email", "at", rf"[{NAME}](?<![{NAME}]{{2}})[{NAME}]*+\x20?[(\[{{]\x20?(?i:at)\x20?[)\]}}]\x20?[A-Za-z0-9-]++(?:\x20?[(\[{{]\x20?(?i:dot)\x20?[)\]}}]\x20?[A-Za-z0-9-]++|\.[A-Za-z0-9-]++)++"),
    ("card", "", r"(?<![0-9])(?<![0-9]-)(?:[0-9]{13,19}|[0-9]{4}([\x20-])[0-9]{4}\1[0-9]{4}\1[0-9]{4}|3[47][0-9]{2}[\x20-][0-9]{6}[\x20-][0-9]{5})(?![0-9])"),
    ("phone", "", r"(?<![0-9+(./-])(?<![0-9)]\x20)(?:\([0-9]{3}\)\x20?[0-9]{3}[\x20.-][0-9]{4}|[0-9]{3}([.-])[0-9]{3}\1[0-9]{4}|00[1-9][0-9]{0,2}(?:[\x20.-][0-9]{2,4}){2,4}|0[1-9][0-9]{1,3}[\x20/-][0-9]{3,4}[\x20-]?[0-9]{3,4})(?![0-9-])"),
    ("ip", ":", r"(?<![0-9A-Fa-f:])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Fa-f:])"),
)
#: Gazetteers: fixed values.
ENDINGS = ("com", "net", "org", "edu", "gov", "info", "io", "de", "fr", "es", "uk", "eu")
DIALLING = ("1", "7", "20", "27", "30", "31", "32", "33", "34", "36", "39", "40", "41", "43", "44", "45", "46", "47", "48", "49", "52", "54", "55", "61", "62", "81", "82", "86", "90", "91", "351", "353", "358", "420")
CUES = {
    "email": r"(?i)(?:e-?mail|mail|contact|write|correo|courriel|kontakt)\W*$",
    "ip": r"(?i)(?:\bip|address|host|server|login|addr)\W*$",
    "card": r"(?i)(?:card|visa|mastercard|amex|credit|payment|tarjeta|carte|karte)\W*(?:no\.?|number)?\W*$",
    "phone": r"(?i)(?:phone|tel|call|fax|mobile|cell|ring|telefon|llame|appelez)\W*$",
}
AGAINST = r"(?i)(?:version|order|invoice|isbn|ref|page|line|section|build|id|no\.?|nr\.?|#)\W*$"
CONTEXT = 30
ACCEPT, ROUNDS = 0.9, 50


def luhn(digits: Column) -> Column:
    """The check sum of card numbers, over a string of digits."""
    n = F.length(digits)
    each = F.transform(F.sequence(F.lit(1), n), lambda i: F.substring(digits, i, F.lit(1)).cast("int") * F.when((n - i) % 2 == 1, 2).otherwise(1))
    return F.aggregate(each, F.lit(0), lambda a, x: a + F.when(x > 9, x - 9).otherwise(x)) % 10 == 0


def _strict(kind: str, match: Column) -> Column:
    """The check that a well-formed value passes: that of the base pattern, or its like for looser spans."""
    digits = F.regexp_replace(match, "[^0-9]", "")
    n = F.length(digits)
    if kind == "ip":
        part = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
        return match.rlike(rf"^{part}(?:\.{part}){{3}}$") | (F.contains(match, F.lit(":")) & match.rlike("^[23]"))
    if kind == "card":
        return F.when(n.between(12, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return n.between(9, 15) & (match.startswith("+") | match.rlike(r"^(?:00|0|\([2-9]|[2-9])[0-9]"))
    return match.rlike(r"^[^@]+@[^@]+$|(?i)dot|\.")


def _gazetteer(kind: str, match: Column) -> Column:
    """1, 0 (no opinion) or -1."""
    if kind == "email":
        return F.when(F.lower(F.regexp_extract(match, r"([A-Za-z]+)$", 1)).isin(*ENDINGS), 1).otherwise(-1)
    if kind == "phone":
        code = F.regexp_extract(match, r"^\+([0-9]{1,3})", 1)
        known = F.substring(code, 1, 1).isin(*DIALLING) | F.substring(code, 1, 2).isin(*DIALLING) | code.isin(*DIALLING)
        plain = F.when(match.rlike(r"^00(?:[1-9])"), 1).when(match.rlike(r"^\(?[2-9][0-9]{2}\)?[\x20.-]?[2-9][0-9]{2}[\x20.-][0-9]{4}$"), 1).otherwise(0)
        return F.when(code == "", plain).when(known, 1).otherwise(-1)
    if kind == "card":
        digits = F.regexp_replace(match, "[^0-9]", "")
        return F.when(digits.rlike("^(?:4|5[1-5]|2[2-7]|3[47]|6011|65)") & F.length(digits).between(13, 16), 1).when(F.length(digits) < 12, -1).otherwise(0)
    return F.when(match.rlike(r"^(?:0|22[4-9]|2[3-5][0-9]|127)\."), -1).otherwise(1)


def _by_kind(make) -> Column:
    out = None
    for k in KINDS:
        out = F.when(F.col("kind") == k, make(k)) if out is None else out.when(F.col("kind") == k, make(k))
    return out


def _found(kind: str, pattern: str, sign: str, base: bool) -> Column:
    """Array of (kind, base, i, gap, match, before): ``gap`` is the text's length between this match and the one before."""
    text = F.col("text")
    tried = F.contains(text, F.lit(sign)) if sign else text.rlike("[0-9]")
    gaps, hits = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    cut = lambda g: F.right(g, F.lit(CONTEXT))
    rows = F.transform(hits, lambda m, i: F.struct(F.lit(kind).alias("kind"), F.lit(base).alias("base"), i.alias("i"), F.lit(0).alias("gap"), m.alias("match"), F.lit("").alias("before")))
    with_gaps = F.zip_with(rows, F.transform(F.slice(gaps, F.lit(1), F.size(hits)), lambda g: F.struct(F.length(g).alias("n"), cut(g).alias("t"))), lambda r, g: F.struct(r["kind"].alias("kind"), r["base"].alias("base"), r["i"].alias("i"), g["n"].alias("gap"), r["match"].alias("match"), g["t"].alias("before")))
    return F.when(tried & (F.size(hits) > 0), with_gaps).otherwise(F.array().cast("array<struct<kind:string,base:boolean,i:int,gap:int,match:string,before:string>>"))


def candidates(docs: DataFrame) -> DataFrame:
    """One row per candidate span, and one without a kind per document without candidates."""
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    arrays = [_found(k, PATTERNS[k], SIGNS[k], True) for k in KINDS] + [_found(k, p, sign, False) for k, sign, p in LOOSE]
    spans = rows.select("row", "doc_id", F.explode_outer(F.concat(*arrays)).alias("s")).select("row", "doc_id", "s.*")
    so_far = Window.partitionBy("row", "kind", "base").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    placed = spans.withColumn("end", F.sum(F.col("gap") + F.length("match")).over(so_far)).withColumn("start", F.col("end") - F.length("match"))
    facts = placed.withColumns({"valid": _by_kind(lambda k: _strict(k, F.col("match"))), "gazetteer": _by_kind(lambda k: _gazetteer(k, F.col("match"))), "cue": _by_kind(lambda k: F.when(F.col("before").rlike(CUES[k]), 1).when(F.col("before").rlike(AGAINST), -1).otherwise(0))})
    facts = facts.withColumn("form", F.when(F.col("valid"), 1).otherwise(-1))
    digits = F.length(F.regexp_replace("match", "[^0-9]", ""))
    shape = F.array(F.concat(F.lit("n"), F.least(digits, F.lit(20)).cast("string")), F.concat(F.lit("l"), F.least(F.floor(F.length("match") / 4), F.lit(12)).cast("string")), F.concat(F.lit("s"), F.regexp_replace(F.regexp_replace("match", "[A-Za-z0-9]+", ""), r"(.)\1+", "$1").substr(1, 3)), F.when(F.col("before").rlike(r"[A-Za-z0-9.]$"), "b1").otherwise("b0"), F.concat(F.lit("c"), F.col("cue").cast("string")), F.concat(F.lit("g"), F.col("gazetteer").cast("string")))
    return facts.withColumn("shape", F.when(F.col("kind").isNotNull(), shape)).drop("i", "gap", "before", "match")


# ---------------------------------------------------------------- label model
def estimate(patterns: list[tuple[str, int, int, int, int]]) -> dict[tuple[str, int, int, int], float]:
    """Expectation-maximisation for labelers that vote independently given the truth, per kind.

    ``patterns``: (kind, votes..., count). Returns the posterior of each pattern. Labelers begin
    at 80 % right, which fixes which of the two classes is the true one."""
    out = {}
    for kind in {p[0] for p in patterns}:
        own = [(p[1:4], p[4]) for p in patterns if p[0] == kind]
        total = sum(n for _, n in own)
        share = 0.5
        table = [{c: {1: 0.6 if c else 0.15, 0: 0.25, -1: 0.15 if c else 0.6} for c in (0, 1)} for _ in range(3)]
        post = {}
        for _ in range(ROUNDS):
            for votes, _n in own:
                yes = math.log(share) + sum(math.log(table[j][1][v]) for j, v in enumerate(votes))
                no = math.log(1 - share) + sum(math.log(table[j][0][v]) for j, v in enumerate(votes))
                post[votes] = 1 / (1 + math.exp(min(700, no - yes)))
            share = min(0.999, max(0.001, sum(post[v] * n for v, n in own) / total))
            for j in range(3):
                for c in (0, 1):
                    mass = {v: 2.0 * (0.6 if (v == 1) == bool(c) and v else 0.2) for v in (1, 0, -1)}
                    for votes, n in own:
                        mass[votes[j]] += n * (post[votes] if c else 1 - post[votes])
                    s = sum(mass.values())
                    table[j][c] = {v: m / s for v, m in mass.items()}
        out.update({(kind, *v): p for v, p in post.items()})
    return out


def _soft_labels(spans: DataFrame) -> DataFrame:
    counted = small_rows(spans.where("kind is not null").groupBy("kind", "form", "gazetteer", "cue").count(), len(KINDS) * 27, "vote patterns")
    post = estimate([tuple(r) for r in counted])
    rows = [(*k, float(p)) for k, p in sorted(post.items())]
    table = spans.sparkSession.createDataFrame(rows, "kind string, form int, gazetteer int, cue int, truth double")
    return spans.join(F.broadcast(table), ["kind", "form", "gazetteer", "cue"], "left")


def classify(spans: DataFrame) -> DataFrame:
    """Adds ``p``, the final classifier's probability of each candidate."""
    spans = _soft_labels(spans)
    prior = spans.where("kind is not null").groupBy("kind").agg(F.sum("truth").alias("yes"), F.sum(1 - F.col("truth")).alias("no"))
    each = spans.where("kind is not null").select("kind", "truth", F.explode("shape").alias("f")).groupBy("kind", "f").agg(F.sum("truth").alias("fy"), F.sum(1 - F.col("truth")).alias("fn"))
    rows = small_rows(each.join(prior, "kind"), 50_000, "shape features")
    weight = {(r.kind, r.f): math.log((r.fy + 0.5) / (r.yes + 1)) - math.log((r.fn + 0.5) / (r.no + 1)) for r in rows}
    base = {r.kind: math.log((r.yes + 0.5) / (r.no + 0.5)) for r in rows}
    table = spans.sparkSession.createDataFrame([(k, {f: w for (x, f), w in weight.items() if x == k}, b) for k, b in sorted(base.items())], "kind string, weights map<string,double>, prior double")
    logit = F.col("prior") + F.aggregate("shape", F.lit(0.0), lambda a, f: a + F.coalesce(F.element_at("weights", f), F.lit(0.0)))
    return spans.join(F.broadcast(table), "kind", "left").withColumn("p", 1 / (1 + F.exp(-logit)))


def report(docs: DataFrame) -> DataFrame:
    """One row per document; null or empty texts have no spans."""
    spans = classify(materialise(candidates(docs), "candidates"))
    base = F.col("base") & F.col("valid")
    kept = spans.withColumn("is_base", F.coalesce(base, F.lit(False))).withColumn("added", F.coalesce(~F.col("is_base") & (F.col("p") >= ACCEPT) & F.when(F.col("base"), F.col("cue") == 1).otherwise(F.col("valid")), F.lit(False)))
    order = F.array_position(F.array(*map(F.lit, KINDS)), F.col("kind"))
    item = F.struct(F.col("start").alias("start"), order.alias("o"), F.col("end").alias("end"), F.col("kind").alias("kind"))
    grouped = kept.groupBy("row", "doc_id").agg(*[F.count_if(F.col("is_base") & (F.col("kind") == k)).alias(f"n_{k}") for k in KINDS], F.array_sort(F.collect_list(F.when(F.col("is_base"), item))).alias("b"), F.collect_list(F.when(F.col("added"), item)).alias("m"))
    free = F.filter("m", lambda x: ~F.exists("b", lambda y: (y["start"] < x["end"]) & (x["start"] < y["end"])))
    none = F.slice(F.col("m"), F.lit(1), F.lit(0))
    free = F.aggregate(F.array_sort(free), none, lambda kept, x: F.when(F.exists(kept, lambda y: (y["start"] < x["end"]) & (x["start"] < y["end"])), kept).otherwise(F.array_append(kept, x)))
    said = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    return grouped.select("doc_id", *(f"n_{k}" for k in KINDS), F.sha2(said(F.col("b")), 256).alias("base_sha256"), said(F.array_sort(F.concat("b", free))).alias("spans"))
