"""Personal data by weak supervision; DataFrame operations only.

Strict patterns give base spans, which always stay. Looser patterns give candidates: spelled-out addresses, phone
numbers without a country sign that are no part of a longer number, labelled secrets quoted or bare, keys with a known
prefix, private key blocks, and national and bank numbers. Four labelers vote yes, no or nothing on every candidate and base span: a
stricter pattern of its kind, a gazetteer of endings and prefixes that speak for it and of fillers that speak against it,
the words before it, likewise for and against, and its shape. Expectation-maximisation over the number of texts of each vote pattern
estimates each labeler's reliability for each class without labels, starting from a weak belief that labelers are
right more often than not; its posteriors then train the final classifier, a logistic model over votes and kind,
whose accepted patterns are applied to the candidates. Vote patterns are at most kinds * 3**4, whatever the data.

Possessive repeats and look-behinds keep the patterns linear on long runs and match as the plain ones do. Places and
overlaps come from sums and maxima over all earlier spans of a text, taken in chunks, so a text of many spans costs little more than its length.

Defined results: a null or empty text has no spans; spans are in code points, end exclusive; candidates that
overlap a base span are dropped, and of accepted candidates one that begins within an earlier one (ties: of earlier
kind) is dropped; repeated rows give equal results; an empty table stays empty; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import stored, table

_LOCAL = r"[A-Za-z0-9._%+-]"
#: kind -> (cheap guard, pattern); the order is the order of output.
BASE = {
    "email": ("instr(text, '@') > 0", rf"(?:(?<!{_LOCAL})|\G){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": (r"text rlike '[0-9]\\.[0-9]'", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"),
    "card": ("text rlike '[0-9](?:[ -]?[0-9]){15}'", r"(?<![0-9])(?<![0-9][ -])[0-9](?:[ -]?[0-9]){15,18}+(?![0-9])(?![ -][0-9])"),
    "phone": ("instr(text, '+') > 0", r"\+[0-9][ ().0-9-]+[0-9]"),
}
LOOSE = {
    "email_spelled": ("text rlike '[\\\\[(]at[\\\\])]'", r"[A-Za-z0-9._%+-]++ ?[\[(]at[\])] ?[A-Za-z0-9-]++(?:(?:\.| ?[\[(]dot[\])] ?)[A-Za-z0-9-]++)++"),
    "phone_local": ("text rlike '[0-9]{3}[ .-][0-9]{4}'", r"(?<![0-9]|[0-9][ .()-]|[0-9]\)[ .-]|[0-9][ .-]\()(?:\([0-9]{3}\)[ .-]?|[0-9]{3}\)?[ .-])[0-9]{3}[ .-][0-9]{4}(?![0-9]|[.-][0-9])"),
    "secret": ("text rlike '[=:]'", r"(?i:token|secret|passw(?:or)?d|passphrase|pwd|api[_-]?key|access[_-]?key|credential)s?+[\"']? *+(?:=>|=|:) *+(?:\"[^\"\s]{6,}+\"|'[^'\s]{6,}+'|[^\s\"',;]{6,}+)"),
    "access_key": ("text rlike '(?:AKIA|ASIA|AIza|gh[pousr]_|xox[abprs]-|sk[-_]|glpat-|eyJ)'", r"(?<![A-Za-z0-9_-])(?:AKIA|ASIA|AIza|gh[pousr]_|xox[abprs]-|sk[-_]|glpat-|eyJ)[A-Za-z0-9_-]{12,}+(?:\.[A-Za-z0-9_-]++)*+"),
    "private_key": ("instr(text, '-----BEGIN ') > 0", r"-----BEGIN [A-Z ]*+-----[A-Za-z0-9+/=\s]*+(?:-----END [A-Z ]*+-----)?"),
    "national_id": ("text rlike '[0-9]{3}-[0-9]{2}-[0-9]{4}'", r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"),
    "iban": ("text rlike '[A-Z]{2}[0-9]{2} ?[A-Z0-9]{4}'", r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}+(?: ?[A-Z0-9]{1,3})?+(?![A-Za-z0-9])"),
}
KINDS = [*BASE, *LOOSE]
_TOP = r"\.(com|org|net|edu|gov|io|de|fr|es|uk)$"
#: What only a candidate that is right should match; base spans have passed theirs.
STRICT = {
    "email_spelled": r"(?:\.| ?[\[(]dot[\])] ?)[A-Za-z]{2,}$",
    "phone_local": r"^\(?[2-9][0-9]{2}\)?[ .-]?[2-9][0-9]{2}[ .-][0-9]{4}$",
    "secret": r"[=:>] *[\"']?(?=\S*[0-9])(?=\S*[A-Za-z])[^\s\"']{10,}[\"']?$",
    "access_key": r"^(?:(?:AKIA|ASIA)[A-Z0-9]{16}|AIza[A-Za-z0-9_-]{35}|gh[pousr]_[A-Za-z0-9]{36,}|xox[abprs]-[0-9].*|sk[-_].*[0-9].*|glpat-[A-Za-z0-9_-]{20,}|eyJ[A-Za-z0-9_-]+\.[A-Za-z0-9_-]+\..*)$",
    "private_key": r"PRIVATE KEY-----\s*\S{16}",
    "national_id": r"^(?!000|666|9)[0-9]{3}-(?!00)[0-9]{2}-(?!0000)[0-9]{4}$",
    "iban": r"^(?:AT|BE|CH|DE|DK|ES|FI|FR|GB|IE|IT|LU|NL|NO|PL|PT|SE)[0-9]{2}",
}
#: (for, against): endings, prefixes and fillers of the span itself.
GAZETTEER = {
    "email": (_TOP, r"@localhost|\.(png|jpe?g|gif|js|css)$"),
    "ip": (r"^(10|172|192)\.", r"^0\."),
    "card": (r"^(4|5[1-5]|3[47]|6)", r"^([0-9])(?:[ -]?\1){7}"),
    "phone": (r"^\+(1|33|34|44|49)([^0-9]|$)", r"^\+0"),
    "email_spelled": (_TOP[2:], r"^(look|meet|arrive|stay)"),
    "phone_local": (r"^\(", r"^\(?[01]|([0-9])\1{3}$"),
    "secret": (r"(?i)^(token|secret|passw|pwd|api)", r"(?i)(example|change.?me|your|xxxx|\*\*\*|none|null|true|false|[=:>] *[\"']?[a-z]+[\"'.!?]*$)"),
    "access_key": (r"^(AKIA|ASIA|AIza|gh[pousr]_|xox|glpat-)", r"(?i)(example|xxxx|your)"),
    "private_key": (r"(RSA|EC|DSA|OPENSSH|ENCRYPTED) PRIVATE", r"PUBLIC|CERTIFICATE"),
    "national_id": (r"^[0-7]", r"^(123-45-6789|078-05-1120)|([0-9])\2\2-\2\2"),
    "iban": (r"^(DE|FR|ES|GB)", r"([0-9])\1{7}"),
}
#: (for, against): words shortly before a span.
_NUMBERED = "version|isbn|page|order|invoice|figure|section|chapter|item|part|build|commit"
CONTEXT = {
    "email": ("mail|contact|write|address", "src|href|file"),
    "ip": ("ip|host|server|addr", _NUMBERED),
    "card": ("card|visa|credit|account", _NUMBERED),
    "phone": ("phone|call|tel|mobile|fax", _NUMBERED),
    "email_spelled": ("mail|contact|write|address", "look|meet|arrive"),
    "phone_local": ("phone|call|tel|mobile|fax", _NUMBERED),
    "secret": ("auth|login|config|credential|set|export", "word|term|called|named"),
    "access_key": ("key|aws|token|secret|auth|bearer|credential", "hash|commit|file"),
    "private_key": ("key|ssh|secret", "public|certificate"),
    "national_id": ("ssn|social|security|tax", _NUMBERED),
    "iban": ("iban|account|bank|transfer", _NUMBERED),
}
SHAPE = {
    "email": r"^.{5,254}$",
    "ip": r"^[0-9.]{7,15}$",
    "card": r"^[0-9]{4}([ -]?)[0-9]{4}\1[0-9]{4}\1[0-9]{4,7}$",
    "phone": r"^\+[0-9]{1,3}[ .(-]",
    "email_spelled": r"[\[(]dot[\])]",
    "phone_local": r"^\([0-9]{3}\) ?[0-9]{3}-|^[0-9]{3}([ .-])[0-9]{3}\1",
    "secret": r"[=:>].*([0-9].*[A-Za-z]|[A-Za-z].*[0-9])",
    "access_key": r"[0-9].*[A-Z]|[A-Z].*[0-9]",
    "private_key": r"END [A-Z ]*-----$",
    "national_id": r"^[0-9]{3}-[0-9]{2}-[0-9]{4}$",
    "iban": r"^[A-Z]{2}[0-9]{2}( ?[A-Z0-9]{4})+( ?[A-Z0-9]{1,3})?$",
}


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


_CHUNK = 128


def _let(value: Column, f) -> Column:
    """``f`` of a value that is computed once, however often ``f`` names it."""
    return F.transform(F.array(value), f)[0]


def _before(values: Column, fold) -> Column:
    """For each element the ``fold`` of all elements before it: of whole chunks, then of the rest."""
    at = lambda i: F.floor(i / _CHUNK).cast("int")
    heads = lambda v: F.transform(F.sequence(F.lit(0), at(F.size(v))), lambda c: fold(F.slice(v, c * _CHUNK + 1, F.lit(_CHUNK))))
    one = lambda v, h: F.transform(v, lambda x, i: fold(F.concat(F.slice(h, F.lit(1), at(i)), F.slice(v, at(i) * _CHUNK + 1, i % _CHUNK))))
    return _let(values, lambda v: _let(heads(v), lambda h: one(v, h)))


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda a, x: a + x)


def _most(values: Column) -> Column:
    return F.coalesce(F.array_max(values), F.lit(0))


def _found(pattern: str, guard: str) -> Column:
    """array<struct<s, e, t>> of all matches: the pieces between matches give the places."""
    p = _quoted(pattern)
    empty = F.expr("CAST(array() AS ARRAY<STRUCT<s: INT, e: INT, t: STRING>>)")
    pairs = F.expr(f"filter(arrays_zip(split(text, {p}, -1), regexp_extract_all(text, {p}, 0)), z -> z['1'] IS NOT NULL)")
    step = lambda z: F.struct(F.length(z["0"]).alias("g"), F.length(z["1"]).alias("n"), z["1"].alias("t"))
    place = lambda z, i, b: F.struct((b[i] + z["g"]).alias("s"), (b[i] + z["g"] + z["n"]).alias("e"), z["t"].alias("t"))
    walk = _let(F.transform(pairs, step), lambda v: _let(_before(F.transform(v, lambda z: z["g"] + z["n"]), _sum), lambda b: F.transform(v, lambda z, i: place(z, i, b))))
    return F.when(F.col("text").isNotNull() & F.expr(guard), walk).otherwise(empty)


def _digits(t: Column) -> Column:
    return F.regexp_replace(t, "[^0-9]", "")


def _luhn(t: Column) -> Column:
    """Sum of digits, every second from the right doubled, is a multiple of ten."""
    d = F.filter(F.split(F.reverse(_digits(t)), ""), lambda x: x != "")
    odd = F.transform(d, lambda x, i: F.when(i % 2 == 0, x.cast("int")).otherwise(F.when(x.cast("int") > 4, x.cast("int") * 2 - 9).otherwise(x.cast("int") * 2)))
    return F.aggregate(odd, F.lit(0), lambda a, x: a + x) % 10 == 0


_VALID = {
    "email": lambda t: F.lit(True),
    "ip": lambda t: ~F.exists(F.split(t, r"\."), lambda x: F.coalesce(F.regexp_replace(x, "^0+(?=[0-9])", "").try_cast("int"), F.lit(999)) > 255),
    "card": _luhn,
    "phone": lambda t: F.length(_digits(t)).between(8, 15),
}


def _holds(kind: str):
    return lambda x: _VALID[kind](x["t"])


def _voted(kind: str):
    return lambda x: F.struct(F.lit(KINDS.index(kind)).alias("k"), x["s"].alias("s"), x["e"].alias("e"), _votes(kind, x).alias("votes"))


def spans_of(docs: DataFrame) -> DataFrame:
    """Adds ``base``, an array of spans a kind, and ``loose``, the candidates with their vote patterns."""
    out = docs
    for kind, (guard, pattern) in BASE.items():
        out = out.withColumn(f"b_{kind}", F.filter(_found(pattern, guard), _holds(kind)))
    for kind, (guard, pattern) in LOOSE.items():
        out = out.withColumn(f"l_{kind}", _found(pattern, guard))
    every = []
    for kind in KINDS:
        col = f"{'b' if kind in BASE else 'l'}_{kind}"
        every.append(F.transform(col, _voted(kind)))
    return out.withColumn("every", F.concat(*every)).drop(*[f"l_{k}" for k in LOOSE])


def _said(yes: Column, no: Column) -> Column:
    return F.when(no, "0").when(yes, "1").otherwise("-")


def _votes(kind: str, x: Column) -> Column:
    """One character a labeler: 1 yes, 0 no, - no opinion."""
    before = F.lower(F.substring(F.col("text"), F.greatest(x["s"] - 23, F.lit(1)), F.least(x["s"], F.lit(24))))
    near = lambda words: before.rlike(rf"(?:{words})\W*\w*\W*$")
    strict = F.lit("1") if kind in BASE else F.when(x["t"].rlike(STRICT[kind]), "1").otherwise("0")
    named = _said(*(x["t"].rlike(r) for r in GAZETTEER[kind]))
    around = _said(*(near(w) for w in CONTEXT[kind]))
    shape = F.when(x["t"].rlike(SHAPE[kind]), "1").otherwise("0")
    return F.concat(F.lit(f"{KINDS.index(kind)}:"), strict, named, around, shape)


def reliabilities(counts: dict[str, int], rounds: int = 200, belief: float = 0.8, worth: float = 10.0) -> tuple[dict[str, float], list[tuple[float, float]]]:
    """(posterior of each vote pattern, (chance of yes if right, chance of yes if wrong) of each labeler), by expectation-maximisation.

    ``counts`` has the spans of each pattern ("kind:votes"). A labeler's two chances are estimated over all kinds from the
    votes it gave; having no opinion says nothing. Each starts as if ``worth`` votes had shown it right with ``belief``,
    which also keeps the classes from changing places; the share of right spans is one for each kind.
    """
    votes = {p: p.split(":")[1] for p in counts}
    kind = {p: p.split(":")[0] for p in counts}
    n = max(map(len, votes.values()), default=0)
    chance = [(belief, 1 - belief)] * n
    prior = dict.fromkeys(kind.values(), 0.5)
    post: dict[str, float] = {}
    for _ in range(rounds):
        new = {}
        for p, v in votes.items():
            odds = math.log(prior[kind[p]] / (1 - prior[kind[p]]))
            for (right, wrong), x in zip(chance, v, strict=True):
                if x != "-":
                    odds += math.log(right / wrong) if x == "1" else math.log((1 - right) / (1 - wrong))
            new[p] = 1 / (1 + math.exp(-max(-30.0, min(30.0, odds))))
        moved = max((abs(new[p] - post.get(p, 0.5)) for p in new), default=0)
        post = new
        for k in prior:
            mine = [(counts[p], post[p]) for p in counts if kind[p] == k]
            prior[k] = (1 + sum(m * w for m, w in mine)) / (2 + sum(m for m, _ in mine))
        for j in range(n):
            yes, given = [belief * worth, (1 - belief) * worth], [worth, worth]
            for p, v in votes.items():
                if v[j] != "-":
                    for c, w in ((0, post[p]), (1, 1 - post[p])):
                        given[c] += counts[p] * w
                        yes[c] += counts[p] * w * (v[j] == "1")
            chance[j] = (yes[0] / given[0], yes[1] / given[1])
        if moved < 1e-7:
            break
    return post, chance


def _solved(a: list[list[float]], b: list[float]) -> list[float]:
    """x of a x = b for a positive definite matrix, by elimination."""
    n, m = len(b), [[*r, v] for r, v in zip(a, b, strict=True)]
    for i in range(n):
        for k in range(i + 1, n):
            f = m[k][i] / m[i][i]
            m[k] = [x - f * y for x, y in zip(m[k], m[i], strict=True)]
    out = [0.0] * n
    for i in reversed(range(n)):
        out[i] = (m[i][n] - sum(m[i][k] * out[k] for k in range(i + 1, n))) / m[i][i]
    return out


def classifier(counts: dict[str, int], post: dict[str, float], rounds: int = 30, ridge: float = 0.5) -> dict[str, float]:
    """A logistic model over votes and kind, fitted to the posteriors with ridge by Newton steps; its score of each pattern."""
    feats = {p: [f"k{p.split(':')[0]}", *[f"{j}{x}" for j, x in enumerate(p.split(":")[1]) if x != "-"]] for p in counts}
    names = sorted({f for fs in feats.values() for f in fs})
    at = {f: i for i, f in enumerate(names)}
    w = [0.0] * len(names)

    def score(p: str) -> float:
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, sum(w[at[f]] for f in feats[p])))))

    for _ in range(rounds):
        g = [ridge * v for v in w]
        h = [[ridge * (i == j) for j in range(len(names))] for i in range(len(names))]
        for p, m in counts.items():
            s = score(p)
            for f in feats[p]:
                g[at[f]] += m * (s - post[p])
                for e in feats[p]:
                    h[at[f]][at[e]] += m * s * (1 - s)
        step = _solved(h, g)
        size = max(map(abs, step), default=0.0)
        w = [v - d * min(1.0, 4 / size if size else 1.0) for v, d in zip(w, step, strict=True)]
        if size < 1e-6:
            break
    return {p: score(p) for p in counts}


def accepted(spans: DataFrame, cut: float = 0.5) -> list[str]:
    """Vote patterns that the trained classifier takes as personal data. A text counts once for each of its patterns, so
    that one text of very many alike spans decides nothing."""
    rows = spans.select(F.explode(F.array_distinct("every.votes")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("n")).collect()
    counts = {r["v"]: r["n"] for r in rows}
    scores = classifier(counts, reliabilities(counts)[0])
    return sorted(p for p, s in scores.items() if s >= cut and int(p.split(":")[0]) >= len(BASE))


def _final(patterns: list[str]) -> Column:
    """All spans: base ones, and accepted candidates that overlap none of them and begin within no earlier one."""
    base = F.filter("every", lambda x: x["k"] < len(BASE))
    listed = F.array(*[F.lit(p) for p in patterns]).cast("array<string>")
    order = F.array_sort(F.transform("every", lambda x: F.struct(x["s"].alias("s"), x["k"].alias("k"), x["e"].alias("e"), x["votes"].alias("votes"))))
    far = 1 << 30

    def free(v: Column) -> Column:
        """Accepted candidates without a base span that reaches into them from before or begins in them."""
        fixed = lambda x: x["k"] < len(BASE)
        reach = _before(F.transform(v, lambda x: F.when(fixed(x), x["e"]).otherwise(0)), _most)
        ahead = F.reverse(_before(F.reverse(F.transform(v, lambda x: F.when(fixed(x), far - x["s"]).otherwise(0))), _most))
        clear = lambda x, i, r, a: ~fixed(x) & F.array_contains(listed, x["votes"]) & (r[i] <= x["s"]) & (far - a[i] >= x["e"])
        return _let(reach, lambda r: _let(ahead, lambda a: F.filter(v, lambda x, i: clear(x, i, r, a))))

    first = lambda v: _let(_before(F.transform(v, lambda x: x["e"]), _most), lambda r: F.filter(v, lambda x, i: r[i] <= x["s"]))
    named = lambda v: F.transform(v, lambda x: F.struct(x["k"].alias("k"), x["s"].alias("s"), x["e"].alias("e"), x["votes"].alias("votes")))
    more = _let(order, lambda v: _let(free(v), lambda u: named(first(u))))
    kept = F.array_sort(more)
    return F.when(F.exists("every", lambda x: x["k"] >= len(BASE)), F.concat(base, kept)).otherwise(base)


def _listed(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", names[x["k"]], x["s"].cast("string"), x["e"].cast("string"))), ",")


def find(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, base, spans) of each document; ``base`` and ``spans`` are arrays."""
    held = stored(spans_of(docs.select("doc_id", "text")).drop("text"), "pii-spans")
    patterns = accepted(held)
    counts = [F.size(f"b_{k}").cast("long").alias(f"n_{k}") for k in BASE]
    return held.withColumn("spans", _final(patterns)).select("doc_id", *counts, F.filter("every", lambda x: x["k"] < len(BASE)).alias("base"), "spans")


def redact(docs: DataFrame, patterns: list[str] | None = None) -> DataFrame:
    """The documents with every span replaced by its kind in angle brackets; all columns stay."""
    names = docs.columns
    if patterns is None:
        patterns = accepted(stored(spans_of(docs.select("text")).select("every"), "pii-votes"))
    rows = spans_of(docs).withColumn("__spans", F.array_sort(F.transform(_final(patterns), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["k"].alias("k")))))
    # overlapping base spans of different kinds are cut as one stretch
    labels = F.array(*[F.lit(f"<{k}>") for k in KINDS])
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("at"))
    step = lambda a, x: F.when(x["s"] < a["at"], F.struct(a["out"].alias("out"), F.greatest(a["at"], x["e"]).alias("at"))).otherwise(F.struct(F.concat(a["out"], F.substring(F.col("text"), a["at"] + 1, x["s"] - a["at"]), labels[x["k"]]).alias("out"), x["e"].alias("at")))
    done = F.aggregate("__spans", start, step, lambda a: F.concat(a["out"], F.substring(F.col("text"), a["at"] + 1, F.lit(2**31 - 1))))
    clean = rows.withColumn("text", F.when(F.size("__spans") > 0, done).otherwise(F.col("text")))
    return clean.select(*names)


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = find(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", *[f"n_{k}" for k in BASE], F.sha2(_listed(F.col("base")), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))
