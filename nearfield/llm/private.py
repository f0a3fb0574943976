"""Personal data: generated candidate spans, boosted trees, calibrated thresholds.

Generators with high recall propose spans that may overlap: every match of the
strict formats, whether or not it passes its check, and of five loose ones, the last
of which is for secrets (keys, tokens, passwords), a kind without a strict format.
Each candidate is described by format features (kind, digits, separators, check
digit, ...) and context features (what stands before and after, a cue word).
All features have few values, so the whole corpus sums up to a table whose size
depends on the features alone; gradient-boosted trees are fitted to that table
on the driver and go back to Spark as one column expression.  A threshold for
each kind is calibrated on the fold of documents that the trees haven't seen:
the lowest score from which on the wanted share of candidates is right, among
all of the kind and among those that can be added.

A loose candidate is right if it is the place of a strict span that passed, or if
its match, brought to the usual form ((at) and (dot) undone, 00 for +, separators
dropped), passes a check of its own: a host with a top domain of letters, a
telephone's length and grouping, a card's length and check digit, a secret's name
just before it.  The trees see format and context, not that check.

Strict spans that pass their check always stay; the model adds spans beside
them.  Everything on the executors is built-in functions.

Positions come from cutting the text at the matches: the lengths of what lies
between and of the matches add up to code-point offsets in one pass.  Patterns
are possessive and start at a run's start or where the last match ended, which
changes no match but keeps long runs of digits or letters linear.

Defined results: a null or empty text has no spans; rows that repeat a doc_id
are treated each for itself; an empty table gives an empty table; a corpus
without right or without wrong candidates adds no spans; other columns pass.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from nearfield.llm.common import keep

#: The kinds in the order of results.
KINDS = ("email", "ip", "card", "phone")
#: All kinds of spans: secrets have no strict format, so only the model adds them.
SPAN_KINDS = (*KINDS, "secret")
#: The strict formats, as possessive Java patterns.
STRICT = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Loose formats: the kind that each may be, and its pattern.
LOOSE = (
    # The first ends where a sentence does.
    ("email", r"(?i)(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+\x20?(?:@|\(at\)|\[at\])\x20?[A-Za-z0-9-]{1,63}+(?:(?:\.|\x20\.\x20|\x20?(?:\(dot\)|\[dot\])\x20?)[A-Za-z0-9-]{1,63}+){1,8}+"),
    ("email", r"(?i)(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+\x20?(?:@|\(at\)|\[at\])\x20?[A-Za-z0-9-]{1,63}+(?:\x20?(?:\.|\(dot\)|\[dot\])\x20?[A-Za-z0-9-]{1,63}+){1,8}+"),
    ("phone", r"(?<![0-9A-Za-z+])(?:00|\()?[0-9](?:[\x20()./-]{0,2}[0-9]){8,18}+"),
    ("card", r"(?<![0-9A-Za-z])[0-9]{4}[./_\x20-][0-9]{4}[./_\x20-][0-9]{4}[./_\x20-][0-9]{1,7}"),
    ("secret", r"(?<![A-Za-z0-9_+/=-])[A-Za-z0-9_+/=-]{20,}+"),
)
#: A text without this holds no match of the kind.
NEEDS = {"email": "[@(\\[]", "ip": "[0-9]", "card": "[0-9]", "phone": "[0-9]", "secret": "[A-Za-z0-9_+/=-]{20}"}
#: Words before a span that speak for it.
CUES = r"(?i)(?:mail|contact|write|tel|phone|call|fax|mobil|card|visa|account|pay|iban|addr|host|server|login|ip|token|secret|key|passw|pwd|auth|bearer)[^\n]{0,12}$"
#: What names a secret just before it.
NAMED = r"(?i)(?:token|secret|key|password|passwd|pwd|auth|bearer)[\"']?\s*[:=]?\s*[\"']?$"

_PART = r"0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5])"
_DIGITS = r"[^0-9]"

FEATURES = ("kind", "strict", "digits", "joined", "plus", "luhn", "parts", "dotted", "cue", "before", "after", "size", "spaced")


def _right(kind: Column, match: Column) -> Column:
    """Whether a strict match passes the check of its kind."""
    digits = F.regexp_replace(match, _DIGITS, "")
    return (
        F.when(kind == "email", F.lit(True))
        .when(kind == "ip", match.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$"))
        .when(kind == "card", F.length(digits).between(13, 19) & F.call_function("luhn_check", F.when(F.length(digits).between(13, 19), digits).otherwise("1")))
        .otherwise(F.length(digits).between(9, 15))
    )


def _fits(kind: str, match: Column, before: Column, after: Column) -> Column:
    """Whether a loose match, brought to the usual form, passes the check of its kind."""
    if kind == "secret":
        good = before.rlike(NAMED) & match.rlike("(?i)^(?:[0-9a-f]{20,}|[A-Za-z0-9_+=-]{20,})$")
    elif kind == "email":
        joined = F.regexp_replace(F.regexp_replace(match, r"(?i)\x20?(?:@|\(at\)|\[at\])\x20?", "@"), r"(?i)\x20?(?:\(dot\)|\[dot\])\x20?|\x20\.\x20", ".")
        good = joined.rlike(r"^[A-Za-z0-9_%+-]+(?:\.[A-Za-z0-9_%+-]+)*@(?:[A-Za-z0-9](?:[A-Za-z0-9-]*[A-Za-z0-9])?\.)+[A-Za-z]{2,24}$")
    elif kind == "card":
        good = _right(F.lit("card"), match)
    else:
        number = F.regexp_replace(F.regexp_replace(match, "^00", ""), _DIGITS, "")
        grouped = r"^00\x20?[1-9]|^\(?0[1-9][0-9]*\)?[\x20./-]|\([0-9]{2,5}\)|^(?:1[\x20.-])?[0-9]{3}[\x20.-][0-9]{3}[\x20.-][0-9]{4}$"
        other = r"^[0-9]{4}([./-])[0-9]{1,2}\1[0-9]{1,2}(?![0-9])|^[0-9]{1,2}([./-])[0-9]{1,2}\2[0-9]{4}(?![0-9])|^[0-9]{1,3}(?:\.[0-9]{1,3}){3}$"
        even = F.regexp_count(match, F.lit(r"\(")) == F.regexp_count(match, F.lit(r"\)"))
        good = F.length(number).between(9, 15) & match.rlike(grouped) & ~match.rlike(other) & even
    return good & ~F.coalesce(after, F.lit("")).rlike("^[A-Za-z0-9]")


def _matches(text: Column, kind: str, pattern: str, strict: bool) -> Column:
    """All matches of a pattern in a text, with their places and surroundings."""
    gaps, hits = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    zipped = F.arrays_zip(gaps.alias("gap"), hits.alias("hit"), F.slice(gaps, F.lit(2), F.greatest(F.size(gaps), F.lit(1))).alias("next"))
    empty = F.from_json(F.lit('{"at": 0, "out": []}'), "at bigint, out array<struct<kind:string,strict:boolean,right:boolean,fits:boolean,start:bigint,end:bigint,hit:string,before:string,after:string>>")

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.coalesce(F.length(x["hit"]), F.lit(0))
        found = F.struct(
            F.lit(kind).alias("kind"),
            F.lit(strict).alias("strict"),
            (_right(F.lit(kind), x["hit"]) if strict else F.lit(False)).alias("right"),
            (F.lit(False) if strict else _fits(kind, x["hit"], F.right(x["gap"], F.lit(24)), x["next"])).alias("fits"),
            start.alias("start"),
            end.alias("end"),
            x["hit"].alias("hit"),
            F.right(x["gap"], F.lit(24)).alias("before"),
            F.left(x["next"], F.lit(2)).alias("after"),
        )
        if kind == "secret":
            # A long word is no candidate, a long number is one of other kinds.
            worth = (F.regexp_count(x["hit"], F.lit("[0-9]")) >= 4) & (F.regexp_count(x["hit"], F.lit("[A-Za-z]")) >= 4)
        else:
            worth = F.length(F.regexp_replace(x["hit"], _DIGITS, "")) >= 9 if kind in ("card", "phone") else F.lit(True)
        return F.struct(end.alias("at"), F.when(x["hit"].isNotNull() & worth, F.concat(acc["out"], F.array(found))).otherwise(acc["out"]).alias("out"))

    nothing = F.filter(empty["out"], lambda x: F.lit(False))
    return F.when(text.rlike(NEEDS[kind]), F.when(F.size(hits) > 0, F.aggregate(zipped, empty, step, lambda acc: acc["out"])).otherwise(nothing)).otherwise(nothing)


def scan(docs: DataFrame) -> DataFrame:
    """``docs`` with ``found``: the candidates of all generators in each whole text."""
    text = F.coalesce(F.col("text"), F.lit(""))
    every = [_matches(text, k, p, True) for k, p in STRICT.items()] + [_matches(text, k, p, False) for k, p in LOOSE]
    return docs.withColumn("found", F.concat(*every))


def _class_of(letter: Column) -> Column:
    """0 edge, 1 space, 2 letter, 3 digit, 4 anything else."""
    return F.when(F.coalesce(letter, F.lit("")) == "", 0).when(letter.rlike(r"^\s"), 1).when(letter.rlike(r"^\p{L}"), 2).when(letter.rlike("^[0-9]"), 3).otherwise(4)


def features(x: Column) -> list[Column]:
    """The features of a candidate, in the order of FEATURES, each a small int."""
    hit = x["hit"]
    digits = F.regexp_replace(hit, _DIGITS, "")
    n = F.length(digits)
    kind = x["kind"]
    return [
        F.when(kind == "email", 0).when(kind == "ip", 1).when(kind == "card", 2).when(kind == "phone", 3).otherwise(4),
        x["strict"].cast("int"),
        F.when(n < 4, 0).when(n < 9, 1).when(n < 11, 2).when(n < 13, 3).when(n < 16, 4).when(n == 16, 5).when(n < 20, 6).otherwise(7),
        F.when(hit.rlike("[()\\[\\]]"), 3).when(hit.rlike("[ /_]"), 2).when(hit.rlike("-"), 1).otherwise(0),
        F.when(hit.startswith("+"), 2).when(hit.startswith("00"), 1).when(hit.rlike(r"^\(?0"), 3).otherwise(0),
        F.when(n.between(13, 19), F.call_function("luhn_check", F.when(n.between(13, 19), digits).otherwise("1")).cast("int")).otherwise(0),
        hit.rlike(rf"^{_PART}(?:\.{_PART}){{3}}$").cast("int"),
        F.least(F.regexp_count(hit, F.lit(r"\.")), F.lit(4)),
        x["before"].rlike(CUES).cast("int"),
        _class_of(F.right(x["before"], F.lit(1))),
        _class_of(F.left(x["after"], F.lit(1))),
        F.least(F.floor(F.log2(F.greatest(F.length(hit), F.lit(1)))), F.lit(8)).cast("int"),
        hit.rlike(r"\x20[.@]|[.@]\x20").cast("int"),
    ]


@dataclass
class Trees:
    """Boosted trees of two levels over small-int features: a test is ``feature <= cut``."""

    bias: float = 0.0
    trees: list[tuple] = field(default_factory=list)
    thresholds: dict[str, float] = field(default_factory=dict)

    def score(self, rows: np.ndarray) -> np.ndarray:
        out = np.full(len(rows), self.bias)
        for (f, c), (lf, lc, ll, lr), (rf, rc, rl, rr) in self.trees:
            out += np.where(rows[:, f] <= c, np.where(rows[:, lf] <= lc, ll, lr), np.where(rows[:, rf] <= rc, rl, rr))
        return out

    def column(self, given: list[Column]) -> Column:
        total = F.lit(self.bias)
        for (f, c), (lf, lc, ll, lr), (rf, rc, rl, rr) in self.trees:
            low = F.when(given[lf] <= lc, F.lit(ll)).otherwise(F.lit(lr))
            total = total + F.when(given[f] <= c, low).otherwise(F.when(given[rf] <= rc, F.lit(rl)).otherwise(F.lit(rr)))
        return total


def boost(rows: np.ndarray, right: np.ndarray, wrong: np.ndarray, rounds: int = 20, rate: float = 0.3, ridge: float = 1.0) -> Trees:
    """Second-order boosting of the logistic loss on a table of weighted rows."""
    model = Trees(bias=float(np.log((right.sum() + 1) / (wrong.sum() + 1))))
    tests = [(f, c) for f in range(rows.shape[1]) for c in np.unique(rows[:, f])[:-1]] or [(0, rows[:, 0].max() if len(rows) else 0)]
    sides = np.stack([rows[:, f] <= c for f, c in tests])
    weight = right + wrong

    def leaf(g: np.ndarray, h: np.ndarray) -> float:
        return float(-rate * g.sum() / (h.sum() + ridge))

    def best(g: np.ndarray, h: np.ndarray) -> int:
        gl, hl = sides @ g, sides @ h
        gr, hr = g.sum() - gl, h.sum() - hl
        return int(np.argmax(gl**2 / (hl + ridge) + gr**2 / (hr + ridge)))

    for _ in range(rounds):
        p = 1 / (1 + np.exp(-model.score(rows)))
        g, h = weight * p - right, weight * p * (1 - p)
        top = best(g, h)
        tree = [tests[top]]
        for side in (sides[top], ~sides[top]):
            k = best(g * side, h * side)
            tree.append((*tests[k], leaf((g * side)[sides[k]], (h * side)[sides[k]]), leaf((g * side)[~sides[k]], (h * side)[~sides[k]])))
        model.trees.append(tuple((int(t[0]), int(t[1]), *t[2:]) for t in tree))
    return model


def fit(scanned: DataFrame, precision: float = 0.99, least: int = 20) -> Trees:
    """Trees and thresholds from all candidates of all documents.

    A candidate is right if it covers exactly a strict span of its kind that
    passed the check, or if it is loose and fits.  Documents are dealt to two
    folds by their hash: one fits the trees, the other sets each kind's
    threshold, which needs ``least`` right candidates; the wanted precision holds
    for all candidates of the kind and for the fresh ones, which meet no strict
    span that passed.  The collected table is bounded by the values of the features.
    """
    base = F.filter("found", lambda x: x["right"])

    def labelled(x: Column) -> Column:
        place = F.exists("base", lambda y: (x["kind"] == y["kind"]) & (x["start"] == y["start"]) & (x["end"] == y["end"]))
        fresh = ~F.exists("base", lambda y: (x["start"] < y["end"]) & (y["start"] < x["end"]))
        return F.struct(x.alias("x"), (x["fits"] | place).cast("long").alias("y"), fresh.cast("int").alias("fresh"))

    x = F.col("c.x")
    table = (
        scanned.select("doc_id", "found", base.alias("base"))
        .select(F.pmod(F.xxhash64("doc_id"), F.lit(2)).alias("fold"), F.explode(F.transform("found", labelled)).alias("c"))
        .select("fold", "c.fresh", "c.y", *[c.alias(n) for n, c in zip(FEATURES, features(x), strict=True)])
        .groupBy("fold", "fresh", *FEATURES)
        .agg(F.sum("y").alias("right"), F.sum(1 - F.col("y")).alias("wrong"))
        .orderBy("fold", "fresh", *FEATURES)
        .collect()
    )
    if not table:
        return Trees()
    rows = np.array([[r[f] or 0 for f in FEATURES] for r in table])
    right, wrong, fold, fresh = (np.array([r[c] for r in table], float) for c in ("right", "wrong", "fold", "fresh"))
    if not right.sum() or not wrong.sum():
        return Trees()
    one = fold == 0
    model = boost(rows[one], right[one], wrong[one]) if right[one].sum() and wrong[one].sum() else boost(rows, right, wrong)
    scores = model.score(rows)
    for k, kind in enumerate(SPAN_KINDS):
        own = (rows[:, 0] == k) & ~one
        order = np.argsort(-scores[own], kind="stable")
        ordered = scores[own][order]
        hits, all_ = np.cumsum(right[own][order]), np.cumsum((right + wrong)[own][order])
        new = fresh[own][order]
        new_hits, new_all = np.cumsum(right[own][order] * new), np.cumsum((right + wrong)[own][order] * new)
        # A threshold takes all candidates of its score.
        last = np.diff(ordered, append=-np.inf) < 0
        good = np.flatnonzero(last & (hits >= precision * all_) & (new_hits >= precision * new_all) & (hits >= least))
        if len(good):
            model.thresholds[kind] = float(ordered[good[-1]]) - 1e-9
    return model


def select(scanned: DataFrame, model: Trees) -> DataFrame:
    """``scanned`` with ``base`` (strict spans that passed) and ``spans`` (those and what the model adds)."""

    def span(x: Column) -> Column:
        return F.struct(F.array_position(F.array(*map(F.lit, SPAN_KINDS)), x["kind"]).alias("order"), x["start"].alias("start"), x["end"].alias("end"), x["kind"].alias("kind"))

    base = F.array_sort(F.transform(F.filter("found", lambda x: x["right"]), span))
    if not model.thresholds:
        return scanned.withColumn("base", base).withColumn("spans", F.col("base"))

    def chosen(x: Column) -> Column:
        limit = F.lit(float("inf"))
        for kind, t in model.thresholds.items():
            limit = F.when(x["kind"] == kind, F.lit(t)).otherwise(limit)
        return ~x["right"] & (x["score"] >= limit)

    def scored(x: Column) -> Column:
        return F.struct(*[x[c].alias(c) for c in ("kind", "strict", "right", "start", "end")], model.column(features(x)).alias("score"))

    def meets(x: Column, y: Column) -> Column:
        return (x["start"] < y["end"]) & (y["start"] < x["end"])

    def beats(y: Column, x: Column) -> Column:
        """An order without ties between different spans: score, length, place, kind."""
        better = (y["score"] > x["score"]) | ((y["score"] == x["score"]) & ((y["end"] - y["start"] > x["end"] - x["start"]) | ((y["end"] - y["start"] == x["end"] - x["start"]) & ((y["start"] < x["start"]) | ((y["start"] == x["start"]) & (y["kind"] < x["kind"]))))))
        return meets(x, y) & better

    return (
        scanned.withColumn("base", base)
        .withColumn("_fresh", F.filter("found", lambda x: ~x["right"] & ~F.exists("base", lambda y: meets(x, y))))
        .withColumn("_more", F.array_distinct(F.filter(F.transform("_fresh", scored), chosen)))
        .withColumn("_more", F.filter("_more", lambda x: ~F.exists("_more", lambda y: beats(y, x))))
        .withColumn("spans", F.array_sort(F.concat("base", F.transform("_more", span))))
        .drop("_fresh", "_more")
    )


def _listed(spans: str) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")


def digest(picked: DataFrame) -> DataFrame:
    count: Callable[[str], Column] = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long")
    return picked.select("doc_id", *[count(k).alias(f"n_{k}") for k in KINDS], F.sha2(F.encode(_listed("base"), "UTF-8"), 256).alias("base_sha256"), _listed("spans").alias("spans"), F.size(F.filter("spans", lambda x: x["kind"] == "secret")).cast("long").alias("n_secret"))


def find(docs: DataFrame) -> DataFrame:
    """One row for each row of ``docs``: its doc_id, its candidates, ``base`` and ``spans``."""
    scanned = keep(scan(docs.select("doc_id", "text")).select("doc_id", "found"))
    return select(scanned, fit(scanned))


def redacted(text: Column, spans: Column) -> Column:
    """The text with each span replaced by its kind in angle brackets; overlapping spans go as one."""
    ordered = F.array_sort(F.transform(spans, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), x["kind"].alias("kind"))))
    begin = F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        fresh = x["start"] >= acc["at"]
        cut = F.concat(acc["out"], F.substring(text, (acc["at"] + 1).cast("int"), (x["start"] - acc["at"]).cast("int")), F.lit("<"), x["kind"], F.lit(">"))
        return F.struct(F.greatest(acc["at"], x["end"]).alias("at"), F.when(fresh, cut).otherwise(acc["out"]).alias("out"))

    done = F.aggregate(ordered, begin, step)
    return F.concat(done["out"], F.substring(text, (done["at"] + 1).cast("int"), F.lit(2**31 - 1)))
