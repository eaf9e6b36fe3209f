"""Personal data by weak supervision, in DataFrame functions only.

Candidates are matches of strict patterns (the base: email, ip, card, phone) and of looser
ones. Labelers vote on each candidate or abstain: the strict pattern with its checks, the
shape, a gazetteer of words that announce the kind, words that announce something else, and
the characters around the span. Some can only say yes, some only no, so abstaining is an outcome
of its own that tells something too. Expectation-maximisation on the counted vote patterns gives
how often each labeler says yes, no or nothing of true and of false spans, and each pattern's posterior; a logistic regression on votes and
span features, fitted to these posteriors, decides about looser candidates. Base spans stay.

Matches and what stands between them come from two regular-expression functions, so offsets
are running sums of lengths and no text is scanned once per match. Patterns start only where a
run of their characters starts (or where the last match ended), which keeps them linear.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Workspace

KINDS = ("email", "ip", "card", "phone")
_LOCAL = "[A-Za-z0-9._%+-]"
#: The base patterns; a start inside a run of their characters can't match where the run's start doesn't.
BASE = {
    "email": rf"(?:\G|(?<!{_LOCAL})){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9]++(?:[\x20-][0-9]++)*+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Cheap tests without which a pattern has no match that passes.
HINT = {"email": "contains({t}, '@')", "ip": r"{t} rlike '[0-9]\\.[0-9]++\\.[0-9]++\\.[0-9]'", "card": r"{t} rlike '[0-9](?:[ -]?[0-9]){{12}}'", "phone": "contains({t}, '+')"}
LOOSE = {
    "email": rf"(?<!{_LOCAL}){_LOCAL}++(?: at |\x20?[\[(]at[\])]\x20?)[A-Za-z0-9-]++(?: dot |\x20?[\[(]dot[\])]\x20?|\.)[A-Za-z]{{2,12}}(?![A-Za-z0-9])",
    "ip": r"(?<![0-9A-Za-z:.])(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}(?![0-9A-Za-z:.])",
    "phone": r"(?<![0-9+(.-])(?<![0-9+]\x20)(?:\([0-9]{3}\)\x20?|[0-9]{3}[.\x20-])[0-9]{3}[.\x20-][0-9]{4}(?![0-9])(?![.\x20-][0-9])",
}
LOOSE_HINT = {
    "email": r"({t} rlike '[ \\[(]at[ \\])]' and {t} rlike '[ \\[(]dot[ \\])]|\\.[A-Za-z]')",
    "ip": r"{t} rlike '[0-9A-Fa-f]:[0-9A-Fa-f]{{1,4}}:[0-9A-Fa-f]'",
    "phone": r"{t} rlike '[0-9]{{3}}[.) -]++[0-9]{{3}}[. -][0-9]{{4}}'",
}
#: Words in front of a span that announce its kind, and words that announce something else.
GAZETTEER = {
    "email": "e-?mail|mail|contact|write|reach|correo|courriel|schreib",
    "ip": "ip|host|server|address|addr|from|client|node",
    "card": "card|visa|master|amex|payment|paid|credit|debit|karte|tarjeta|carte",
    "phone": "phone|call|tel|telephone|fax|mobile|cell|ring|dial|whatsapp|telefon|tel[eé]fono",
}
AGAINST = "version|release|section|chapter|isbn|issn|order|invoice|ticket|serial|doi|build|v"
LABELERS = ("strict", "shape", "gazetteer", "against", "edges")


def quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def let(value: str, name: str, body: str) -> str:
    """SQL that evaluates value once and gives body, in which name stands for it."""
    return f"element_at(transform(array({value}), {name} -> {body}), 1)"


def over_matches(text: str, pattern: str, hint: str, body: str, otherwise: str) -> str:
    """SQL of body where text has matches: z.p is what stands between them, z.m the matches."""
    p = quoted(pattern)
    split = f"named_struct('p', split(t, {p}, -1), 'm', regexp_extract_all(t, {p}, 0))"
    return let(text, "t", f"if({hint.format(t='t')}, {let(split, 'z', body)}, {otherwise})")


def matches(kind: str, base: bool) -> str:
    """SQL: structs of all matches of a kind in `text`, in order, with a little of what surrounds them."""
    pattern, hint = (BASE[kind], HINT[kind]) if base else (LOOSE[kind], LOOSE_HINT[kind])
    one = f"named_struct('kind', '{kind}', 'base', {str(base).lower()}, 'place', i, 'skip', bigint(length(z.p[i])), 'before', right(z.p[i], 41), 'found', f, 'after', left(z.p[i + 1], 1))"
    return over_matches("text", pattern, hint, f"transform(z.m, (f, i) -> {one})", "array()")


def valid(kind: str, match: str) -> str:
    """SQL: whether a base match passes its checks."""
    digits = f"regexp_replace({match}, '[^0-9]', '')"
    if kind == "ip":
        return f"{match} rlike '^(0*(25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(\\\\.|$)){{4}}$'"
    if kind == "phone":
        return f"length({digits}) between 9 and 15"
    if kind == "card":
        weigh = f"transform(sequence(1, length({digits})), k -> int(substr({digits}, -k, 1)) * (2 - k % 2))"
        luhn = f"aggregate({weigh}, 0, (s, d) -> s + if(d > 9, d - 9, d)) % 10 = 0"
        return f"case when length({digits}) between 13 and 19 then {luhn} else false end"
    return "true"


def votes(kind: str, strict: bool, before: str, found: str, after: str) -> dict[str, str]:
    """SQL of each labeler on the span and what surrounds it: 1, 0, or -1 to abstain."""
    ahead = f"lower(right({before}, 40))"
    digits = f"regexp_replace({found}, '[^0-9]', '')"
    shape = {
        "email": f"if({found} rlike '[.](com|org|net|edu|gov|io|de|fr|es|uk|eu|info|example)$', 1, -1)",
        "ip": f"if({found} rlike '^(0|127|255)[.]', 0, 1)",
        "card": f"if({digits} rlike '^(4|5[1-5]|3[47]|6011|65|2[2-7])', 1, 0)",
        "phone": f"if({digits} rlike '^([0-9])\\\\1+$', 0, 1)",
    }[kind]
    return {
        "strict": "1" if strict else "-1",
        "shape": shape,
        "gazetteer": f"if({ahead} rlike {quoted(rf'(?<![a-z])({GAZETTEER[kind]})(?![a-z])')}, 1, -1)",
        "against": f"if({ahead} rlike {quoted(rf'(?<![a-z])({AGAINST})[ .:#]*$')}, 0, -1)",
        "edges": f"if(right({before}, 1) rlike '[A-Za-z0-9]' or left({after}, 1) rlike '[A-Za-z0-9]', 0, 1)",
    }


def spans_features(found: str) -> dict[str, str]:
    return {
        "digits": f"int(least(length(regexp_replace({found}, '[^0-9]', '')) div 4, 5))",
        "marks": f"int(least(length(regexp_replace({found}, '[0-9A-Za-z]', '')), 6))",
    }


def candidates(docs: DataFrame) -> DataFrame:
    """doc, version, kind, base, start, finish, votes and span features of each candidate; docs: doc, version, text."""
    kinds = [(k, True) for k in BASE] + [(k, False) for k in LOOSE]
    every = docs.select("doc", "version", F.expr(f"concat({', '.join(matches(*k) for k in kinds)})").alias("all"))
    # The outer form, as the plain one makes the optimiser evaluate the array once more in a filter.
    every = every.select("doc", "version", F.explode_outer("all").alias("x")).where("x is not null").select("doc", "version", "x.*")
    every = every.dropDuplicates(["doc", "version", "kind", "base", "place"])

    def by_kind(of) -> Column:
        return F.expr("case " + " ".join(f"when kind = '{k}' and base = {str(b).lower()} then {of(k, b)}" for k, b in kinds) + " end")

    columns = {n: by_kind(lambda k, b, n=n: votes(k, b, "before", "found", "after")[n]) for n in LABELERS}
    columns |= {n: F.expr(v) for n, v in spans_features("found").items()}
    columns |= {"ok": by_kind(lambda k, b: valid(k, "found") if b else "true"), "size": F.length("found").cast("bigint")}
    every = every.select("doc", "version", "kind", "base", "place", "skip", *(c.alias(n) for n, c in columns.items()))
    w = Window.partitionBy("doc", "version", "kind", "base").orderBy("place").rowsBetween(Window.unboundedPreceding, 0)
    placed = every.withColumn("finish", F.sum(F.col("skip") + F.col("size")).over(w)).withColumn("start", F.col("finish") - F.col("size"))
    return placed.where("ok").drop("place", "skip", "size", "ok")


@dataclass(frozen=True)
class Model:
    """Chances of a labeler's vote (no, yes, none) for false and true spans, the share of true spans
    by kind, and the classifier's weights by feature."""

    chance: dict[str, list[list[float]]]
    prior: dict[str, float]
    weights: dict[str, float]

    def score(self, values: dict[str, str]) -> str:
        """SQL of the classifier's log-odds; values: the SQL of kind, votes and span features."""
        terms = [repr(self.weights.get("bias", 0.0))]
        for name, weight in self.weights.items():
            if name != "bias":
                column, level = name.split(" = ")
                terms.append(f"{weight!r} * int({values.get(column, column)} = {level})")
        return " + ".join(f"({t})" for t in terms)


def features(row: dict) -> list[str]:
    out = [f"{n} = {row[n]}" for n in LABELERS]
    return out + [f"kind = '{row['kind']}'", f"digits = {row['digits']}", f"marks = {row['marks']}"]


#: What a vote is thought to say before any is counted, of false and of true spans, in votes: no, yes, none.
BELIEF = {
    "strict": ([0.0, 1.0, 7.0], [0.0, 6.0, 2.0]), "shape": ([3.0, 2.0, 3.0], [1.0, 5.0, 2.0]), "gazetteer": ([0.0, 1.0, 7.0], [0.0, 4.0, 4.0]),
    "against": ([3.0, 0.0, 5.0], [0.5, 0.0, 7.5]), "edges": ([4.0, 4.0, 0.0], [1.0, 7.0, 0.0]),
}


def fit(rows: list[dict], rounds: int = 60, steps: int = 300) -> Model:
    """EM and classifier on counted patterns (kind, votes, digits, marks, n): a few thousand rows at most."""
    floor = 0.05  # of a vote, so that no outcome is impossible
    total = sum(r["n"] for r in rows) or 1

    def chances(counts: list[list[float]]) -> list[list[float]]:
        return [[(x + floor) / (sum(side) + 3 * floor) for x in side] for side in counts]

    chance = {n: chances([list(side) for side in BELIEF[n]]) for n in LABELERS}
    prior = dict.fromkeys(KINDS, 0.5)
    truth = [0.5] * len(rows)
    for _ in range(rounds if rows else 0):
        for k, r in enumerate(rows):
            odds = math.log(prior[r["kind"]] / (1 - prior[r["kind"]])) + sum(math.log(chance[n][1][r[n]] / chance[n][0][r[n]]) for n in LABELERS)
            truth[k] = 1 / (1 + math.exp(-max(-30.0, min(30.0, odds))))
        for n in LABELERS:
            counts = [list(side) for side in BELIEF[n]]
            for r, t in zip(rows, truth, strict=True):
                counts[1][r[n]] += r["n"] * t
                counts[0][r[n]] += r["n"] * (1 - t)
            chance[n] = chances(counts)
        for kind in KINDS:
            seen = [(r["n"], t) for r, t in zip(rows, truth, strict=True) if r["kind"] == kind]
            prior[kind] = min(0.95, max(0.05, (sum(n * t for n, t in seen) + 2) / (sum(n for n, _ in seen) + 4)))
    weights: dict[str, float] = {"bias": 0.0}
    named = [features(r) for r in rows]
    for _ in range(steps if rows else 0):
        slope: dict[str, float] = {}
        for r, t, names in zip(rows, truth, named, strict=True):
            p = 1 / (1 + math.exp(-max(-30.0, min(30.0, weights["bias"] + sum(weights.get(n, 0.0) for n in names)))))
            g = r["n"] * (p - t) / total
            for n in ["bias", *names]:
                slope[n] = slope.get(n, 0.0) + g
        for n, g in slope.items():
            weights[n] = weights.get(n, 0.0) * (1 - 1e-3) - 1.0 * g
    return Model(chance, prior, {n: round(w, 6) for n, w in sorted(weights.items())})


def learn(found: DataFrame) -> Model:
    """Patterns are counted on the cluster; their number has a fixed bound (kinds, votes and buckets)."""
    counted = found.groupBy("kind", *LABELERS, "digits", "marks").agg(F.count(F.lit(1)).alias("n"))
    return fit(sorted((r.asDict() for r in counted.collect()), key=str))


def keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("bigint").alias("doc"), F.xxhash64(text).alias("version"), text.alias("text"))


def listed(name: str) -> str:
    return f"array_join(transform(array_sort(filter(spans, x -> {name})), x -> concat(element_at(array('email', 'ip', 'card', 'phone'), x.kind), ':', x.start, ':', x.finish)), ',')"


def personal_data(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """doc_id, counts of base spans by kind, their digest, and all spans, for every row of docs (doc_id, text).

    Null texts count as empty. Offsets count code points. Looser spans are added where the
    classifier's probability reaches `least` and no base span of their kind overlaps; without any
    candidate nothing is added. Rows with equal id and text get the same spans; extra columns
    are ignored.
    """
    rows = keyed(docs)
    found = Workspace(docs.sparkSession, "pii").write(candidates(rows), "candidates")
    model = learn(found)
    odds = math.log(least / (1 - least))
    kept = found.where(F.col("base") | (F.expr(model.score({})) >= odds))
    spans = kept.groupBy("doc", "version").agg(F.collect_list(F.struct(F.expr("array_position(array('email', 'ip', 'card', 'phone'), kind)").cast("int").alias("kind"), "start", "finish", "base")).alias("spans"))
    clear = "filter(spans, x -> x.base or not exists(spans, y -> y.base and y.kind = x.kind and y.start < x.finish and x.start < y.finish))"
    spans = spans.withColumn("spans", F.expr(clear))
    joined = rows.select("doc", "version").join(spans.select(F.col("doc").alias("d"), F.col("version").alias("v"), "spans"), F.expr("doc <=> d and version = v"), "left").withColumn("spans", F.coalesce("spans", F.expr("cast(array() as array<struct<kind:int,start:bigint,finish:bigint,base:boolean>>)")))
    counts = [F.expr(f"size(filter(spans, x -> x.base and x.kind = {k + 1}))").cast("bigint").alias(f"n_{kind}") for k, kind in enumerate(KINDS)]
    return joined.select(F.col("doc").alias("doc_id"), *counts, F.sha2(F.expr(listed("x.base")).cast("binary"), 256).alias("base_sha256"), F.expr(listed("true")).alias("spans"))


def masked(docs: DataFrame, least: float = 0.5) -> DataFrame:
    """The pipeline's stage: the same columns with every span in text replaced by its kind in brackets.

    Kinds are masked one after another in the order listed; n_chars follows. Null texts stay null.
    """
    model = learn(candidates(keyed(docs)))
    odds = math.log(least / (1 - least))
    text = "text"
    for base, patterns, hints in ((True, BASE, HINT), (False, LOOSE, LOOSE_HINT)):
        for kind, pattern in patterns.items():
            around = {"before": "z.p[i]", "found": "f", "after": "z.p[i + 1]"}
            values = {"kind": f"'{kind}'"} | votes(kind, base, **around) | spans_features("f")
            test = valid(kind, "f") if base else f"({model.score(values)}) >= {odds!r}"
            pieces = f"transform(z.m, (f, i) -> concat(z.p[i], if({test}, '[{kind.upper()}]', f)))"
            text = over_matches(text, pattern, hints[kind], f"concat(array_join({pieces}, ''), element_at(z.p, -1))", "t")
    out = docs.withColumn("text", F.expr(text))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)
