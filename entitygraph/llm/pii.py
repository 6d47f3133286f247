"""PII spans by candidate gradient boosting, in DataFrame functions only.

Base patterns give spans as they stand. High-recall generators propose further, overlapping spans: the same kinds in other written forms (no country code, other
separators, spelt-out signs) and secrets. Candidates have discrete format and context features. Boosted trees are fitted on the counts of each feature combination over
all texts (there are few combinations, whatever the number of texts). Labels don't come from the generators' own patterns: positive are base spans and what they become in other written forms
(``_mutations``), with the context that they stand in, and strings that a credential's name is assigned to; negative are candidates that fail their kind's own test, digits
without any form, and strings that nothing is assigned to (also the assigned ones, taken out of their context). Candidates with neither label are for the trees to judge: they become a SQL expression, and a threshold calibrated
on the counts selects what is added. Positions are code points.

Spans are a function of the text, so they are keyed by two hashes of id and text: rows without an id, and rows that repeat one with another text, have their own."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from entitygraph.shared import materialise

KINDS = ("email", "ip", "card", "phone", "secret")
#: Base patterns, by kind (fixed values). Atomic runs and the guard before a local part only keep the search linear: an address starts where its run of
#: local characters does, or where the last address ended.
BASE = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: Generators, by kind.
WIDE = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}+(?:@|\x20?(?:\(at\)|\[at\])\x20?)[A-Za-z0-9-]{1,63}+(?:(?:\.|\x20?(?:\(dot\)|\[dot\])\x20?)[A-Za-z0-9-]{1,63}+)++",
    "ip": r"(?<![0-9.])[0-9]{1,3}(?:\.[0-9]{1,3}){3}(?!\.?[0-9])",
    "card": r"(?<![0-9])(?:[0-9]{12,19}|[0-9]{4}(?:[\x20./_-][0-9]{4}){3}|[0-9]{4}[\x20./_-][0-9]{6}[\x20./_-][0-9]{5})(?![0-9])",
    "phone": r"(?<![0-9]|[0-9][./_-])(?:(?:\+|00)[0-9]{1,3}[\x20./-]?)?\(?[0-9]{2,4}\)?[\x20./-]?[0-9]{3,4}[\x20./-]?[0-9]{4}(?![./_-]?[0-9])",
    "secret": r"(?<![A-Za-z0-9+/_-])(?=[A-Za-z+/_-]*+[0-9])(?=[0-9+/_-]*+[A-Za-z])[A-Za-z0-9+/_-]{16,}+"
    r"|(?<=(?i:token|secret|password|passwd|pwd|apikey|api_key|api-key|access_key)['\x22]?\x20{0,2}[=:]\x20{0,2}['\x22]?)[^\s'\x22,;=:]{8,}+",
}
#: Words in the 24 characters before a candidate, by the context that they stand for (fixed values); the second needs an assignment after it.
CUES = (
    r"(?:tel|phone|call|fax|mobile|cell|whatsapp|contact)[^0-9]*$",
    r"(?:token|secret|passw(?:or)?d|pwd|key|auth|bearer)['\x22]?\s*(?:[=:]|\x20)\s*['\x22]?$",
    r"(?:card|visa|master|amex|credit|account)[^0-9]*$",
    r"(?:\bip|host|server|addr(?:ess)?)[^0-9]*$",
    r"(?:mail|write to|reach)\W*$",
)
TREES, RATE, PRECISION = 24, 0.3, 0.95
FEATURES = ("kind", "digits", "valid", "marks", "plus", "before", "after", "cue")
#: Code points that a text is cut into before its pieces are put together.
CHUNK = 4096
KEY = ("k1", "k2")


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the checksum."""
    total = F.aggregate(
        F.sequence(F.lit(1), F.length(digits)),
        F.lit(0),
        lambda acc, i: acc + F.when(i % 2 == 0, _doubled(F.substring(F.reverse(digits), i, F.lit(1)).cast("int"))).otherwise(F.substring(F.reverse(digits), i, F.lit(1)).cast("int")),
    )
    return total % 10 == 0


def _doubled(d: Column) -> Column:
    return 2 * d - F.when(d > 4, 9).otherwise(0)


def _valid(kind: Column, found: Column) -> Column:
    """Whether a match passes its kind's own test."""
    digits = F.regexp_replace(found, "[^0-9]", "")
    n = F.length(digits)
    octet = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
    return (
        F.when(kind == 0, F.lit(True))
        .when(kind == 1, found.rlike(rf"^{octet}(?:\.{octet}){{3}}$"))
        .when(kind == 2, F.when((n >= 12) & (n <= 19), luhn(digits)).otherwise(False))
        .when(kind == 3, (n >= 9) & (n <= 15))
        .otherwise((F.length(found) >= 8) & found.rlike("[0-9]") & found.rlike("[A-Za-z]"))
    )


def _keyed(docs: DataFrame) -> DataFrame:
    """k1, k2 and text, for a key of 128 bits over id and text; null texts are empty."""
    text = F.coalesce("text", F.lit(""))
    return docs.select(*_key(F.col("doc_id"), text), text.alias("text"))


def _key(doc_id: Column, text: Column) -> list[Column]:
    one = F.coalesce(doc_id.cast("string"), F.lit("null"))
    return [F.xxhash64(one, text).alias("k1"), F.xxhash64(text, F.lit(1), one).alias("k2")]


def _matches(texts: DataFrame, patterns: dict[str, str], hint: dict[str, Column]) -> DataFrame:
    """Key, kind, i, gap, found, left, right, cue: the i-th match of each kind, the text's length since the last one, the characters around it, and the context before it."""
    parts = texts.select(
        *KEY,
        *[F.when(hint[k], F.split("text", p, -1)).alias(f"{k}_gaps") for k, p in patterns.items()],
        *[F.when(hint[k], F.regexp_extract_all("text", F.lit(p), F.lit(0))).alias(f"{k}_found") for k, p in patterns.items()],
    )
    ids = {k: i for i, k in enumerate(KINDS)}

    def listed(k: str) -> Column:
        found, gaps = F.col(f"{k}_found"), F.col(f"{k}_gaps")
        zipped = F.arrays_zip(found.alias("found"), gaps.alias("gap"), F.slice(gaps, 2, F.size(gaps)).alias("next"))
        one = lambda x, i: F.struct(
            F.lit(ids[k]).alias("kind"), i.alias("i"), F.length(x["gap"]).alias("gap"), x["found"].alias("found"),
            F.substring(x["gap"], -24, 24).alias("left"), F.substring(x["next"], 1, 1).alias("right"),
        )
        return F.when(F.size(found) > 0, F.transform(zipped, one))

    each = F.concat(*[F.coalesce(listed(k), F.expr("cast(array() as array<struct<kind:int,i:int,gap:int,found:string,left:string,right:string>>)")) for k in patterns])
    rows = parts.select(*KEY, F.explode(each).alias("m")).select(*KEY, "m.*").where("found is not null")
    return rows.dropDuplicates([*KEY, "kind", "i"])


def _placed(matches: DataFrame) -> DataFrame:
    """Adds start and end; one text's matches of a kind are summed in order."""
    upto = Window.partitionBy(*KEY, "kind").orderBy("i")
    return matches.withColumn("end", F.sum(F.col("gap") + F.length("found")).over(upto)).withColumn("start", F.col("end") - F.length("found"))


def _side(c: Column) -> Column:
    return F.when(F.coalesce(c, F.lit("")) == "", 0).when(c.rlike(r"^\s$"), 1).when(c.rlike("^[0-9]$"), 2).when(c.rlike(r"^\p{L}$"), 3).otherwise(4)


def _described(spans: DataFrame) -> DataFrame:
    """Spans with kind, found, left and right get their features."""
    n = F.length(F.regexp_replace("found", "[^0-9]", ""))
    marks = F.length(F.regexp_replace("found", "[0-9A-Za-z]", ""))
    cue = F.lit(0)
    for i, words in reversed(list(enumerate(CUES))):
        cue = F.when(F.lower("left").rlike(words), i + 1).otherwise(cue)
    return (
        spans.withColumn("valid", _valid(F.col("kind"), F.col("found")).cast("int"))
        .withColumn("digits", F.when(n < 4, 0).when(n < 9, 1).when(n < 12, 2).when(n < 16, 3).when(n < 20, 4).otherwise(5))
        .withColumn("marks", F.least(marks, F.lit(7)))
        .withColumn("plus", F.when(F.col("found").startswith("+"), 1).when(F.col("found").startswith("00"), 2).otherwise(0))
        .withColumn("cue", cue)
        .withColumn("before", _side(F.substring("left", -1, 1)))
        .withColumn("after", _side(F.col("right")))
    )


def _hints() -> dict[str, Column]:
    text = F.col("text")
    return {"email": text.contains("@"), "ip": text.rlike(r"[0-9]\.[0-9]"), "card": text.rlike(r"[0-9][\x20-]?[0-9]"), "phone": text.contains("+")}


def base_spans(texts: DataFrame) -> DataFrame:
    """Key, kind (number), start, end, found, left, right: what the base patterns find and their tests keep. texts: key and text."""
    return _placed(_matches(texts, BASE, _hints())).where(_valid(F.col("kind"), F.col("found"))).select(*KEY, "kind", "start", "end", "found", "left", "right")


def candidate_spans(texts: DataFrame) -> DataFrame:
    """The generators' spans with their features."""
    text = F.col("text")
    hint = {
        "email": text.rlike(r"@|[(\[]at[)\]]"), "ip": text.rlike(r"[0-9]\.[0-9]"), "card": text.rlike("[0-9]{4}"), "phone": text.rlike("[0-9]{4}"),
        "secret": text.rlike(r"[0-9]") & text.rlike(r"[A-Za-z0-9+/_-]{16}|(?i:token|secret|passw|pwd|key)"),
    }
    return _described(_placed(_matches(texts, WIDE, hint))).select(*KEY, "start", "end", "found", *FEATURES)


def _mutations(base: DataFrame) -> DataFrame:
    """Base spans in other written forms, in the context that they stand in, with their label: the forms that people use; and, as negatives,
    digits without any form, which could be any number, and card numbers with a wrong check digit."""
    found = F.col("found")
    bare = F.regexp_replace(found, r"^\+[0-9]{1,3}[\x20.-]", "")  # without the country code
    digits = F.regexp_replace(bare, "[^0-9]", "")
    wrong = F.concat(F.expr("substring(regexp_replace(found, '[^0-9]', ''), 1, length(regexp_replace(found, '[^0-9]', '')) - 1)"), ((F.substring(digits, -1, 1).cast("int") + 1) % 10).cast("string"))
    form = lambda c, y: F.struct(c.alias("found"), F.lit(y).alias("y"))
    spelt = F.regexp_replace(found, "@", " (at) ")
    forms = (
        F.when(F.col("kind") == 0, F.array(form(found, 1), form(spelt, 1), form(F.regexp_replace(found, "@", "[at]"), 1), form(F.regexp_replace(spelt, r"\.", " (dot) "), 1)))
        .when(F.col("kind") == 2, F.array(form(found, 1), form(wrong, 0), *[form(F.regexp_replace(d, "([0-9]{4})(?=[0-9])", f"$1{c}"), y) for c in " -./_" for d, y in ((digits, 1), (wrong, 0))]))
        .when(F.col("kind") == 3, F.array(
            form(found, 1), form(bare, 1), form(F.regexp_replace(bare, "[()]", ""), 1), form(F.regexp_replace(found, r"^\+", "00"), 1), form(digits, 0),
            *[form(F.regexp_replace(digits, "^([0-9]{3})([0-9]{3})", f"$1{c}$2{c}"), 1) for c in " -./"],
        ))
        .otherwise(F.array(form(found, 1)))
    )
    return _described(base.select("kind", "left", "right", F.explode(forms).alias("f")).select("kind", "left", "right", "f.found", "f.y")).select(*FEATURES, "y")


class BoostedTrees:
    """Logistic boosting of two-level trees over discrete features, fitted on weighted combinations."""

    def __init__(self, base: float, trees: list):
        self.base, self.trees = base, trees

    @classmethod
    def fit(cls, rows: list[tuple[dict, int, int]], trees: int = TREES, rate: float = RATE) -> BoostedTrees:
        """rows: features, positives, negatives."""
        up, down = sum(r[1] for r in rows) + 1.0, sum(r[2] for r in rows) + 1.0
        model = cls(math.log(up / down), [])
        margin = [model.base] * len(rows)

        def leaf(index):
            g = sum(rows[i][1] - (rows[i][1] + rows[i][2]) * p[i] for i in index)
            h = sum((rows[i][1] + rows[i][2]) * p[i] * (1 - p[i]) for i in index)
            return g, h

        def best(index):
            g, h = leaf(index)
            top = (1e-9, None)
            for f in FEATURES:
                for v in sorted({rows[i][0][f] for i in index}):
                    inside = [i for i in index if rows[i][0][f] == v]
                    gi, hi = leaf(inside)
                    gain = gi * gi / (hi + 1) + (g - gi) ** 2 / (h - hi + 1) - g * g / (h + 1)
                    if gain > top[0] and len(inside) < len(index):
                        top = (gain, (f, v))
            return top[1]

        def grow(index, depth):
            cut = best(index) if depth else None
            if cut is None:
                g, h = leaf(index)
                value = rate * g / (h + 1)
                for i in index:
                    margin[i] += value
                return value
            f, v = cut
            return f, v, grow([i for i in index if rows[i][0][f] == v], depth - 1), grow([i for i in index if rows[i][0][f] != v], depth - 1)

        for _ in range(trees if rows else 0):
            p = [1 / (1 + math.exp(-m)) for m in margin]
            model.trees.append(grow(list(range(len(rows))), 3))
        return model

    def margin(self, features: dict) -> float:
        def walk(t):
            while isinstance(t, tuple):
                t = t[2] if features[t[0]] == t[1] else t[3]
            return t

        return self.base + sum(map(walk, self.trees))

    def column(self) -> Column:
        def expr(t):
            return F.when(F.col(t[0]) == t[1], expr(t[2])).otherwise(expr(t[3])) if isinstance(t, tuple) else F.lit(float(t))

        total = F.lit(float(self.base))
        for t in self.trees:
            total = total + expr(t)
        return total

    def threshold(self, rows: list[tuple[dict, int, int]], precision: float = PRECISION) -> float:
        """The least margin at which candidates of at least that margin are positive as often as asked."""
        order = sorted(((self.margin(f), p, n) for f, p, n in rows), reverse=True)
        least, up, down = math.inf, 0, 0
        for k, (m, p, n) in enumerate(order):
            up, down = up + p, down + n
            if up and up >= precision * (up + down) and (k + 1 == len(order) or order[k + 1][0] < m):
                least = m
        return least


def fit_trees(candidates: DataFrame, base: DataFrame) -> tuple[BoostedTrees, float]:
    """Counts of each combination of features and label; at most a few thousand rows reach the driver, the product of the features' values."""
    assigned = (F.col("kind") == 4) & (F.col("cue") == 2) & (F.col("valid") == 1)
    unfit = (F.col("valid") == 0) | ((F.col("kind") == 4) & (F.col("cue") == 0)) | ((F.col("kind") == 3) & (F.col("marks") == 0) & (F.col("cue") == 0))
    seen = candidates.select(*FEATURES, F.when(assigned, 1).when(unfit, 0).alias("y"))
    loose = seen.where(assigned).select(*[F.lit({"cue": 0, "before": 1, "after": 1}[f]).alias(f) if f in ("cue", "before", "after") else F.col(f) for f in FEATURES], F.lit(0).alias("y"))
    counts = seen.where("y is not null").unionByName(loose).unionByName(_mutations(base)).groupBy(*FEATURES).agg(F.sum("y").alias("up"), F.sum(1 - F.col("y")).alias("down"))
    rows = [({f: r[f] for f in FEATURES}, r["up"], r["down"]) for r in counts.orderBy(*FEATURES).collect()]
    model = BoostedTrees.fit(rows)
    return model, model.threshold(rows)


def _apart(candidates: DataFrame, base: DataFrame) -> DataFrame:
    """The candidates that overlap no base span: by the furthest end of those that start no later, and the nearest start of the others."""
    both = base.select(*KEY, "kind", "start", "end", F.lit(True).alias("base")).unionByName(candidates.select(*KEY, "kind", "start", "end", F.lit(False).alias("base")))
    own = Window.partitionBy(*KEY)
    reach = F.max(F.when(F.col("base"), F.col("end"))).over(own.orderBy("start"))
    ahead = F.min(F.when(F.col("base"), F.col("start"))).over(own.orderBy(F.desc("start")))
    seen = both.withColumn("reach", reach).withColumn("ahead", ahead)
    free = (F.coalesce("reach", F.lit(-1)) <= F.col("start")) & (F.coalesce("ahead", F.lit(1 << 62)) >= F.col("end"))
    return seen.where(~F.col("base") & free).select(*KEY, "kind", "start", "end")


def _spans(texts: DataFrame) -> DataFrame:
    """Key, kind, start, end, base of keyed texts."""
    base = materialise(base_spans(texts), "base-spans")
    candidates = materialise(candidate_spans(texts), "candidates")
    model, least = fit_trees(candidates, base)
    chosen = candidates.where(model.column() >= least).select(*KEY, "kind", "start", "end").distinct()
    added = _apart(chosen, base).withColumn("base", F.lit(False))
    return base.select(*KEY, "kind", "start", "end", F.lit(True).alias("base")).unionByName(added)


def pii_spans(docs: DataFrame) -> DataFrame:
    """doc_id, kind (number), start, end, base: base spans, and accepted candidates that overlap no base span.

    Null and empty texts have no spans; rows without an id have theirs under a null doc_id; rows that repeat an id have their own each, equal rows theirs once; texts of any length are
    searched whole; other columns are ignored, whatever their names; an empty table gives no rows."""
    own = docs.select("doc_id", "text").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    named = own.select("doc_id", *_key(F.col("doc_id"), F.coalesce("text", F.lit("")))).distinct()
    return _spans(_keyed(own)).join(named, list(KEY)).select("doc_id", "kind", "start", "end", "base")


def _joined(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(
        F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ","
    )


def _merged(spans: DataFrame) -> DataFrame:
    """Key and cut: the stretches that spans cover (overlapping ones together), in order, each with its first span's kind."""
    order = Window.partitionBy(*KEY).orderBy("start", "kind", "end")
    before = F.max("end").over(order.rowsBetween(Window.unboundedPreceding, -1))
    fresh = spans.withColumn("fresh", F.when(F.col("start") < before, 0).otherwise(1))
    numbered = fresh.withColumn("island", F.sum("fresh").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    islands = numbered.groupBy(*KEY, "island").agg(F.min(F.struct("start", "kind")).alias("f"), F.max("end").alias("end"))
    return islands.groupBy(*KEY).agg(F.array_sort(F.collect_list(F.struct("f.start", "f.kind", "end"))).alias("cut"))


def _cut_out(text: Column, cut: Column) -> Column:
    """The text with each stretch replaced by its kind's name. The text is cut into chunks once, so that no piece is searched for from the start."""
    chunks = F.regexp_extract_all(text, F.lit(f"(?s).{{1,{CHUNK}}}"), F.lit(0))
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])

    def between(chunks: Column, a: Column, b: Column) -> Column:
        a, b = a.cast("int"), b.cast("int")
        part = lambda c: F.substring(F.get(chunks, c), F.greatest(a - c * CHUNK, F.lit(0)) + 1, F.least(b, (c + 1) * CHUNK) - F.greatest(a, c * CHUNK))
        return F.when(b > a, F.array_join(F.transform(F.sequence(F.floor(a / CHUNK).cast("int"), F.floor((b - 1) / CHUNK).cast("int")), part), "")).otherwise("")

    def written(chunks: Column) -> Column:
        last = lambda i: F.when(i > 0, F.get(cut, i - 1)["end"]).otherwise(0)
        pieces = F.transform(cut, lambda s, i: F.concat(between(chunks, last(i), s["start"]), F.element_at(names, s["kind"] + 1)))
        return F.concat(F.array_join(pieces, ""), between(chunks, F.element_at(cut, -1)["end"], F.length(text)))

    return F.element_at(F.transform(F.array(chunks), written), 1)  # the chunks, named once


def redact(docs: DataFrame) -> DataFrame:
    """The documents with each span (overlapping ones as one) replaced by the name of its first kind in brackets; n_chars, if there, follows the text.

    Every row is kept and redacted by its own text: also rows without an id, and rows that repeat one. Null and empty texts stay; an empty table gives no rows."""
    spans = _merged(_spans(_keyed(docs))).select(F.col("k1").alias("_k1"), F.col("k2").alias("_k2"), F.col("cut").alias("_cut"))
    k1, k2 = _key(F.col("doc_id"), F.coalesce("text", F.lit("")))
    keyed = docs.withColumn("_key1", k1).withColumn("_key2", k2)
    clean = F.when(F.col("_cut").isNull(), F.col("text")).otherwise(_cut_out(F.col("text"), F.col("_cut")))
    out = keyed.join(spans, (F.col("_key1") == F.col("_k1")) & (F.col("_key2") == F.col("_k2")), "left").withColumn("text", clean)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("_cut").isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """n_email to n_phone and base_sha256 are over base spans; spans lists all, secrets among them as a fifth kind."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    span = F.struct("start", "kind", "end", "base")
    per = _spans(_keyed(docs)).groupBy(*KEY).agg(
        F.array_sort(F.collect_list(span)).alias("all"), *[F.sum((F.col("base") & (F.col("kind") == i)).cast("int")).alias(f"n_{k}") for i, k in enumerate(KINDS[:4])]
    )
    return (
        docs.select("doc_id", *_key(F.col("doc_id"), F.coalesce("text", F.lit(""))))
        .join(per, list(KEY), "left")
        .select(
            "doc_id",
            *[F.coalesce(f"n_{k}", F.lit(0)).cast("long").alias(f"n_{k}") for k in KINDS[:4]],
            F.sha2(F.coalesce(_joined(F.filter("all", lambda s: s["base"])), F.lit("")).cast("binary"), 256).alias("base_sha256"),
            F.coalesce(_joined(F.col("all")), F.lit("")).alias("spans"),
        )
    )
