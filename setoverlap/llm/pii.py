"""Personal data by candidate gradient boosting, in built-in functions only.

Generators with high recall propose overlapping spans; fourteen yes/no features of a span's format and of the text
around it form one of 16,384 patterns; boosted regression trees give each pattern a score, a monotone
calibration on labels that the trees have not seen turns it into a probability, and spans above a threshold are
selected beside the validated base spans. The trees learn from seeded labelled samples (spelled-out addresses, national numbers, addresses outside
ASCII, and what looks like them) and from the candidates of the table whose label is known: positive when they
overlap a validated base span, negative when they overlap none and are glued to a word or hold 12 digits or more.
Other candidates of the table are not learned from. The table's counts are scaled down to the number of samples,
so that the size of a corpus does not drown them. Aggregations to at most two rows a pattern reach the driver;
a fifth of the table's labels (by a hash of the candidate) and samples of another seed are kept for calibration.

Defined cases: null text reads as empty (no spans); repeated rows each get a row; an empty table gives an empty
result and a model of the samples alone; other columns are not read. Very long runs of one character class are
scanned once: patterns start only at the head of a run and repeat without backtracking.
"""

from __future__ import annotations

import json
import math
import random
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from setoverlap.llm.common import fenced

KINDS = ["email", "ip", "card", "phone", "other"]
# Java patterns with the language of the contract's, possessive where nothing can follow.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
GENERATORS = {
    "at_word": r"(?:\G|(?<![^\s]))[^\s@]++@[^\s]++",
    "spelled_mail": r"(?i)(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++ ?[\[(](?:at|@)[\])] ?[A-Za-z0-9-]++ ?(?:\.|[\[(]dot[\])]) ?[A-Za-z0-9-]++",
    "digits": r"[+(]?[0-9](?:[\x20().-]{0,2}[0-9]){6,}+",
}
CUES = r"(?i)(?:phone|mobile|tel|fax|call|mail|contact|card|visa|account|konto|iban|ssn|social|addr|reach|write)[^\n]{0,12}$"
# A plain point must stand close to both words; a number's groups as people write them.
SPELLED = r"[\[(](?i:at|@)[\])] ?[A-Za-z0-9-]+(?: ?[\[(](?i:dot)[\])] ?|[.])[A-Za-z]{2,24}$"
GROUPED = r"^(?:\(?0[0-9]{1,4}\)?[ .-]{1,2}[0-9]|\([0-9]{2,5}\) ?[0-9]|[0-9]{3}[ .-][0-9]{3}[ .-][0-9]{4}$)"
CONTEXT = 24
THRESHOLD = 0.9

#: How many yes/no features `_feature_columns` gives.
N_FEATURES = 14
SAMPLES, SEED = 400, 20240101
#: What a candidate's struct holds; `after` is the one character behind it.
_SPANS = "array<struct<s:int,e:int,v:string,before:string,after:string>>"


def _zip_spans(t: Column, pattern: str) -> Column:
    """array<struct<s, e, v, before, after>> of a pattern's matches; what lies between them gives their places."""
    parts, found = F.split(t, pattern, -1), F.regexp_extract_all(t, F.lit(pattern), F.lit(0))
    empty = F.expr(f"cast(array() as {_SPANS})")

    def step(acc: Column, x: Column) -> Column:
        s = acc["at"] + F.length(x["p"])
        e = s + F.length(x["m"])
        item = F.struct(s.alias("s"), e.alias("e"), x["m"].alias("v"), F.substring(x["p"], -CONTEXT, CONTEXT).alias("before"), F.substring(x["q"], 1, 1).alias("after"))
        return F.struct(e.alias("at"), F.concat(acc["out"], F.array(item)).alias("out"))

    pairs = F.transform(found, lambda m, i: F.struct(F.get(parts, i).alias("p"), m.alias("m"), F.get(parts, i + 1).alias("q")))
    return F.aggregate(pairs, F.struct(F.lit(0).alias("at"), empty.alias("out")), step, lambda a: a["out"])


def _valid(kind: str, v: Column) -> Column:
    digits = F.regexp_replace(v, "[^0-9]", "")
    n = F.length(digits)
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        return F.forall(F.split(v, r"\."), lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.coalesce(F.substring(F.ltrim(p, F.lit("0")), 1, 3).try_cast("int"), F.lit(0)) <= 255))
    if kind == "phone":
        return n.between(9, 15)
    places = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.when(i % 2 == 0, c.try_cast("int")).otherwise(c.try_cast("int") * 2 - F.when(c.try_cast("int") > 4, 9).otherwise(0)))
    luhn = F.aggregate(places, F.lit(0), lambda a, x: a + F.coalesce(x, F.lit(0))) % 10 == 0
    return F.when(n.between(12, 19), luhn).otherwise(F.lit(False))


def _no_spans() -> Column:
    return F.expr(f"cast(array() as {_SPANS})")


def candidates(df: DataFrame) -> DataFrame:
    """doc_id, base_<kind> (validated spans) and proposals (spans of the generators that propose beside them)."""
    t = F.coalesce(F.col("text").cast("string"), F.lit(""))
    d = df.withColumn("p_text", t)
    t = F.col("p_text")
    guard = {"email": t.contains("@"), "ip": t.rlike("[0-9][.][0-9]"), "card": t.rlike("[0-9][ -]?[0-9]"), "phone": t.contains("+"), "at_word": t.contains("@"), "spelled_mail": t.rlike(r"[\[(](?i:at|@)[\])]"), "digits": t.rlike("[0-9][ ().-]{0,2}[0-9]")}
    d = d.withColumns({f"raw_{k}": F.when(guard[k], _zip_spans(t, p)).otherwise(_no_spans()) for k, p in (BASE | GENERATORS).items()})
    passing = lambda k: lambda x: _valid(k, x["v"])
    d = d.withColumns({f"base_{k}": F.filter(F.col(f"raw_{k}"), passing(k)) for k in BASE})
    return d.withColumn("proposals", F.concat(*[F.col(f"raw_{g}") for g in GENERATORS])).drop(*[f"raw_{k}" for k in BASE | GENERATORS])


def _overlaps(x: Column, kinds=tuple(BASE)) -> Column:
    hit = F.lit(False)
    for k in kinds:
        hit = hit | F.exists(F.col(f"base_{k}"), lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"]))
    return hit


def _pattern(x: Column) -> Column:
    """The features of a span as one integer below 2^N_FEATURES; of its own text and the text around it."""
    total = F.lit(0)
    for i, sql in enumerate(_feature_columns(x["v"], x["before"], x["after"])):
        total = total + F.when(sql, 1 << i).otherwise(0)
    return total


def _glued(before: Column, after: Column) -> Column:
    return before.rlike(r"[\p{L}0-9_]$") | after.rlike(r"^[\p{L}0-9_]")


def _feature_columns(v: Column, before: Column, after: Column) -> list[Column]:
    digits = F.length(F.regexp_replace(v, "[^0-9]", ""))
    return [
        v.contains("@"), v.rlike(r"@[\p{L}0-9-]+[.][\p{L}0-9-]"), v.startswith("+"), digits.between(9, 11), digits.between(12, 15), digits.between(16, 19),
        v.rlike(r"^[0-9]{1,3}([.][0-9]{1,3}){3}$"), v.rlike("^[0-9]+$"), v.contains("("), before.rlike(CUES),
        v.rlike(SPELLED), _glued(before, after), v.rlike(GROUPED), v.rlike("^[0-9]{3}-[0-9]{2}-[0-9]{4}$"),
    ]


@dataclass
class PatternModel:
    """Probability of personal data for each feature pattern; patterns never seen are scored by the same trees."""

    trees: list[tuple]
    prior: float
    steps: list[tuple[float, float]]

    def margin(self, bits: int) -> float:
        total = self.prior
        for node in self.trees:
            while isinstance(node, tuple):
                node = node[2] if bits >> node[0] & 1 else node[1]
            total += node
        return total

    def probability(self, bits: int) -> float:
        m, p = self.margin(bits), 0.0
        for low, value in self.steps:
            if m >= low:
                p = value
        return p

    def selected(self, threshold: float) -> list[int]:
        return [b for b in range(1 << N_FEATURES) if self.probability(b) >= threshold]


def _grow(rows: list[tuple[int, float, float]], depth: int, shrink: float, least: float):
    """A regression tree on (bits, weight, weighted gradient and curvature folded as Newton leaf)."""
    w, g = sum(r[1] for r in rows), sum(r[2] for r in rows)
    leaf = shrink * g / (w + 1.0)
    if not depth:
        return leaf
    best = (g * g / (w + 1.0) + 1e-9, None)
    for f in range(N_FEATURES):
        on = [r for r in rows if r[0] >> f & 1]
        w1, g1 = sum(r[1] for r in on), sum(r[2] for r in on)
        w0, g0 = w - w1, g - g1
        if min(w0, w1) >= least and (gain := g0 * g0 / (w0 + 1.0) + g1 * g1 / (w1 + 1.0)) > best[0]:
            best = (gain, f)
    if best[1] is None:
        return leaf
    f = best[1]
    return (f, _grow([r for r in rows if not r[0] >> f & 1], depth - 1, shrink, least), _grow([r for r in rows if r[0] >> f & 1], depth - 1, shrink, least))


def fit_patterns(counts: list[tuple[int, float, float]], held: list[tuple[int, float, float]] | None = None, rounds: int = 40, depth: int = 3, shrink: float = 0.3) -> PatternModel:
    """Boost on (bits, candidates, positives), at most 2^N_FEATURES rows, then calibrate by pooling adjacent violators
    of `held`, counts that the trees have not seen (of `counts` where there are none)."""
    n, pos = sum(c[1] for c in counts), sum(c[2] for c in counts)
    if not n:
        return PatternModel([], -20.0, [])
    prior, trees = math.log((pos + 0.5) / (n - pos + 0.5)), []
    score = {b: prior for b, _, _ in counts}
    for _ in range(rounds):
        rows = []
        for b, c, p in counts:
            q = 1 / (1 + math.exp(-max(-30.0, min(30.0, score[b]))))
            rows.append((b, c * q * (1 - q), p - c * q))
        tree = _grow(rows, depth, shrink, 1e-3)
        trees.append(tree)
        for b in score:
            node = tree
            while isinstance(node, tuple):
                node = node[2] if b >> node[0] & 1 else node[1]
            score[b] += node
    pools: list[list[float]] = []
    grown = PatternModel(trees, prior, [])
    for m, c, p in sorted((grown.margin(b), c, p) for b, c, p in held or counts):
        pools.append([m, c, p])
        while len(pools) > 1 and pools[-2][2] * pools[-1][1] >= pools[-1][2] * pools[-2][1]:
            last = pools.pop()
            pools[-1] = [pools[-1][0], pools[-1][1] + last[1], pools[-1][2] + last[2]]
    return PatternModel(trees, prior, [(m, p / (c + 2.0)) for m, c, p in pools])


def labelled_samples(n: int = SAMPLES, seed: int = SEED) -> list[tuple[str, int]]:
    """(text, 1 personal or 0 not): n texts of each kind, one candidate's surroundings in each."""
    r = random.Random(seed)
    digits = lambda k: "".join(r.choices("0123456789", k=k))
    word = lambda: "".join(r.choices("abcdefghilmnoprstuvw", k=r.randint(3, 9)))
    cue = lambda: r.choice(["phone: ", "Tel. ", "call ", "mobile ", "Fax ", "reach me on ", "contact: "])
    plain = lambda: r.choice(["the ", "and then ", "", "in ", "about ", "see: "])
    any_of = lambda: r.choice([cue, plain])()

    def spelled() -> str:
        o, c = r.choice(["[]", "()"])
        gap, at, dot = r.choice(["", " "]), r.choice(["at", "AT", "@"]), r.choice(["dot", "DOT"])
        end = r.choice([f"{gap}{o}{dot}{c}{gap}", "."])
        return r.choice([word(), f"{word()}.{word()}", word() + digits(2)]) + f"{gap}{o}{at}{c}{gap}{word()}{end}{r.choice(['com', 'org', 'net', 'de', 'fr', 'es', 'info'])}"

    def national() -> str:
        return r.choice([f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}", f"{digits(3)}.{digits(3)}.{digits(4)}", f"0{digits(2)} {digits(7)}", f"0{digits(3)}-{digits(6)}", f"(0{digits(2)}) {digits(4)} {digits(3)}", f"0{digits(1)}-{digits(2)}-{digits(2)}-{digits(2)}-{digits(2)}"])

    def date() -> str:
        return r.choice([f"20{digits(2)}-0{r.randint(1, 9)}-1{digits(1)} 1{digits(1)}", f"1{digits(1)}.0{r.randint(1, 9)}.20{digits(2)} 2{digits(1)}", f"20{digits(2)}-1{r.randint(0, 2)}-2{digits(1)}"])

    no_zero = lambda k: r.choice("123456789") + digits(k - 1)
    kinds = [
        (1, lambda: any_of() + spelled()),
        (1, lambda: any_of() + national()),
        (1, lambda: cue() + r.choice([national(), digits(r.randint(9, 11))])),
        (1, lambda: r.choice(["ssn ", "SSN: ", "social security number ", "my SSN is "]) + f"{digits(3)}-{digits(2)}-{digits(4)}"),
        (0, lambda: plain() + f"{digits(3)}-{digits(2)}-{digits(4)}"),
        (1, lambda: any_of() + f"{word()}é{word()}@{word()}ü{word()}.{r.choice(['de', 'fr', 'es', 'org'])}"),
        (0, lambda: f"{plain()}{word()} ({r.choice(['at', 'AT'])}) {word()}. {word().capitalize()} "),
        (0, lambda: any_of() + date()),
        (0, lambda: plain() + digits(r.randint(7, 11))),
        (0, lambda: f"{plain()}{word()}{digits(1)}{r.choice('abcdef')}{digits(r.randint(7, 19))}{r.choice('abcdef')}{digits(2)}"),
        (0, lambda: plain() + " ".join(no_zero(r.randint(1, 3)) for _ in range(r.randint(7, 9)))),
        (0, lambda: plain() + f"{no_zero(r.randint(1, 3))}.{digits(3)}.{digits(3)}.{digits(3)}"),
        (0, lambda: any_of() + f"{word()}@{word()}"),
        (0, lambda: any_of() + ".".join(str(r.randint(256, 999)) for _ in range(4))),
        (0, lambda: f"{plain()}{word()}{national()}" if r.random() < 0.5 else f"{plain()}{national()}{word()}"),
    ]
    return [(f"{make()} {word()}", y) for y, make in kinds for _ in range(n)]


def _counts(proposals: DataFrame) -> list[tuple[int, int, int, int]]:
    """(bits, held out, candidates, positives) of rows (bits, held, hit) with a label."""
    rows = proposals.where("x.hit is not null").groupBy("x.bits", "x.held").agg(F.count("*").alias("n"), F.sum("x.hit").alias("pos")).collect()
    return sorted((r["bits"], r["held"], r["n"], r["pos"]) for r in rows)


def train(df: DataFrame) -> PatternModel:
    """One pass over all rows and one over the samples; only pattern counts (at most 2^15 rows) come to the driver."""
    x = candidates(df.select("text")).select("proposals", *[f"base_{k}" for k in BASE]).where(F.size("proposals") > 0)

    def label(p: Column) -> Column:
        known_not = _glued(p["before"], p["after"]) | (F.length(F.regexp_replace(p["v"], "[^0-9]", "")) >= 12)
        return F.when(_overlaps(p), F.lit(1).cast("long")).when(known_not, F.lit(0).cast("long"))

    def coded(p: Column, hit: Column, held: Column) -> Column:
        return F.struct(_pattern(p).alias("bits"), held.cast("int").alias("held"), hit.alias("hit"))

    fifth = lambda p: F.pmod(F.xxhash64(p["v"], p["before"]), F.lit(5)) == 0
    table = _counts(x.select(F.explode(F.transform("proposals", lambda p: coded(p, label(p), fifth(p)))).alias("x")))
    made = json.dumps([{"text": t, "hit": y, "held": i} for i in (0, 1) for t, y in labelled_samples(seed=SEED + i)])
    rows = df.sparkSession.range(1).select(F.inline(F.from_json(F.lit(made), "array<struct<text:string,hit:bigint,held:int>>")))
    taught = _counts(candidates(rows).select("hit", "held", F.explode("proposals").alias("p")).select(coded(F.col("p"), F.col("hit"), F.col("held")).alias("x")))
    parts: list[list[tuple[int, float, float]]] = []
    for held in (0, 1):
        mine, theirs = ([(b, n, p) for b, h, n, p in rows if h == held] for rows in (taught, table))
        total: dict[int, tuple[float, float]] = {b: (n, p) for b, n, p in mine}
        share = min(1.0, sum(n for _, n, _ in mine) / max(1, sum(n for _, n, _ in theirs)))
        for b, n, p in theirs:
            m, q = total.get(b, (0, 0))
            total[b] = (m + share * n, q + share * p)
        parts.append([(b, n, p) for b, (n, p) in sorted(total.items())])
    return fit_patterns(*parts)


def find(df: DataFrame, model: PatternModel, threshold: float = THRESHOLD) -> DataFrame:
    """Adds p_base and p_spans, arrays of (s, k, e) in order of start and kind, and n_<kind>."""
    c = candidates(df)
    as_span = lambda k: lambda x: F.struct(x["s"].alias("s"), F.lit(KINDS.index(k)).alias("k"), x["e"].alias("e"))
    base = F.sort_array(F.concat(*[F.transform(F.col(f"base_{k}"), as_span(k)) for k in BASE]))
    chosen = model.selected(threshold)
    extra = F.filter("proposals", lambda p: F.lit(False) if not chosen else _pattern(p).isin(chosen) & ~_overlaps(p))
    c = c.withColumns({"p_base": base, "p_extra": F.transform(extra, as_span("other"))} | {f"n_{k}": F.size(f"base_{k}").cast("long") for k in BASE})
    return c.withColumn("p_spans", F.array_distinct(F.sort_array(F.concat("p_base", "p_extra")))).drop("p_extra", "proposals", *[f"base_{k}" for k in BASE])


def written(spans: Column) -> Column:
    name = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", F.get(name, x["k"]), x["s"].cast("string"), x["e"].cast("string"))), ",")


def personal_data(df: DataFrame, model: PatternModel | None = None) -> DataFrame:
    """The digest columns of the contract, one row a document."""
    model = model or train(df)
    d = find(df.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model)
    return fenced(d.select("doc_id", *[f"n_{k}" for k in BASE], F.sha2(written(F.col("p_base")).cast("binary"), 256).alias("base_sha256"), written(F.col("p_spans")).alias("spans")))


def redact(df: DataFrame, model: PatternModel | None = None) -> DataFrame:
    """df with each selected span of text replaced by its kind in angle brackets; overlapping spans go as one."""
    names = df.columns
    model = model or train(df)
    d = find(df.select(F.struct(*[F.col(f"`{c}`") for c in names]).alias("p_row"), "text"), model)
    t, label = F.col("p_text"), F.array(*[F.lit(f"<{k}>") for k in KINDS])

    def step(a: Column, x: Column) -> Column:
        fresh = x["s"] >= a["at"]
        piece = F.concat(F.substring(t, a["at"] + 1, x["s"] - a["at"]), F.get(label, x["k"]))
        return F.struct(F.greatest(a["at"], x["e"]).alias("at"), F.when(fresh, F.concat(a["out"], F.array(piece))).otherwise(a["out"]).alias("out"))

    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<string>)").alias("out"))
    text = F.aggregate("p_spans", start, step, lambda a: F.concat(F.array_join(a["out"], ""), F.substring(t, a["at"] + 1, F.length(t))))
    new = F.when(F.size("p_spans") > 0, text).otherwise(F.col("p_row.text"))
    return fenced(d.select(*[(new.alias("text") if c == "text" else F.col(f"p_row.`{c}`").alias(c)) for c in names]))
