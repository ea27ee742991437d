"""Personal data: base patterns, and bootstrapped contextual extraction of identifiers that no base pattern finds. DataFrame functions only.

Base spans (email, ip, card, phone) are seeds, and so are tokens shaped like a secret (a run of `long` or more letters, digits and -_+/ with at least
four letters and four digits, as keys and hashes are). Seeds and candidate tokens (identifier-like: at least `least` characters with a digit or
an at sign, outside base spans) are instances; the words around an occurrence are its lexical patterns: the two words before it, the
word before with the word after, and a label alone (a word before that ends in a colon or an equals sign). A secret-shaped token is no span by its shape, only
by its context. On this bipartite graph scores spread in turns: a pattern's confidence is the score of its
distinct instances over their number plus one, counted as 0 with fewer than `support` scored instances; an instance that is no seed
scores the noisy-or of its patterns' confidences. After `rounds` turns, a candidate occurrence in a pattern of at least `confident`
becomes a span of kind `id`.

Positions are code points: a text is split at the matches, and lengths of pieces and matches add up (a window sum over the few
matches of a text, never over its characters). Regular expressions are written so that each text takes linear time.

Defined results: null text counts as empty; without spans, base_sha256 is that of the empty string and spans is empty.
Rows with equal doc_id and text get equal results. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Kept, table

KINDS = ("email", "ip", "card", "phone", "id")
#: Base patterns as the contract fixes them; look-behinds only forbid starts within a run that was already tried.
_LOCAL = r"A-Za-z0-9._%+\-"
PATTERNS = {
    "email": rf"(?:(?<![{_LOCAL}])|\G)[{_LOCAL}]+@[A-Za-z0-9\-]++(?:\.[A-Za-z0-9\-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)",
    "card": r"[0-9](?:[ \-]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9\-]+[0-9]",
    "id": r"(?<![^ \t-\r])[^ \t-\r]*[0-9@][^ \t-\r]*",
}
#: A substring without which a kind cannot occur spares its search.
_NEEDS = {"email": "contains(t, '@')", "ip": r"t rlike '[0-9]\\.[0-9]'", "card": "t rlike '[0-9]{2}|[0-9][ -][0-9]'", "phone": "contains(t, '+')", "id": "t rlike '[0-9@]'"}
_GAP = "[ \\t-\\r]+"


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def luhn(digits: str) -> str:
    """SQL: whether a string of digits passes the check sum."""
    d = f"cast(substring({digits}, length({digits}) - i, 1) as int)"
    return f"aggregate(sequence(0, length({digits}) - 1), 0, (s, i) -> s + if(i % 2 = 0, {d}, if({d} > 4, 2 * {d} - 9, 2 * {d}))) % 10 = 0"


def valid(kind: str, m: str) -> str:
    """SQL: whether a match counts."""
    if kind == "ip":
        return f"forall(split({m}, '[.]'), p -> length(ltrim('0', p)) <= 2 or (length(ltrim('0', p)) = 3 and ltrim('0', p) <= '255'))"
    if kind == "card":
        digits = f"translate({m}, ' -', '')"
        return f"(length({digits}) between 12 and 19 and {luhn(digits)})"
    if kind == "phone":
        return f"length(regexp_replace({m}, '[^0-9]', '')) between 9 and 15"
    return "true"


def _matches(docs: DataFrame, least: int) -> DataFrame:
    """docs(key, t) to a row for each match: kind, place, length of the text before it, the match, the words around it."""
    found = []
    for k, kind in enumerate(KINDS):
        p = _quoted(PATTERNS[kind])
        rows = f"transform(arrays_zip(regexp_extract_all(t, {p}, 0), split(t, {p}, -1)), x -> named_struct('kind', {k}, 'm', x.`0`, 'plen', length(x.`1`), 'left', right(x.`1`, 96), 'right', left(x.`1`, 64)))"
        found.append(f"case when {_NEEDS[kind]} then {rows} end")
    every = docs.select("key", F.explode(F.filter(F.array(*map(F.expr, found)), lambda a: a.isNotNull())).alias("of")).select("key", F.posexplode("of").alias("at", "x"))
    every = every.groupBy("key", "x.kind", "at").agg(*(F.first(f"x.{c}").alias(c) for c in ("m", "plen", "left", "right")))
    order = W.partitionBy("key", "kind").orderBy("at")
    every = every.withColumn("start", F.sum(F.col("plen") + F.coalesce(F.length("m"), F.lit(0))).over(order) - F.coalesce(F.length("m"), F.lit(0)))
    every = every.withColumn("after", F.lead("right").over(order)).filter("m is not null").withColumn("end", F.col("start") + F.length("m"))
    ok = "case kind " + " ".join(f"when {k} then {valid(kind, 'm') if kind != 'id' else f'length(m) >= {least}'}" for k, kind in enumerate(KINDS)) + " end"
    before = F.filter(F.split("left", _GAP), lambda x: x != "")
    word = lambda c: F.lower(F.try_element_at(F.filter(F.split(c, _GAP), lambda x: x != ""), F.lit(1)))
    two = F.when(F.size(before) >= 2, F.lower(F.concat_ws(" ", F.try_element_at(before, F.lit(-2)), F.try_element_at(before, F.lit(-1)))))
    one = F.when((F.size(before) >= 1) & word("after").isNotNull(), F.concat(F.lower(F.try_element_at(before, F.lit(-1))), F.lit(" _ "), word("after")))
    last = F.try_element_at(before, F.lit(-1))
    label = F.when(last.rlike("[:=]$"), F.concat(F.lower(last), F.lit(" _")))
    return every.filter(ok).select("key", "kind", F.col("start").cast("long").alias("start"), F.col("end").cast("long").alias("end"), F.lower("m").alias("instance"), F.array_compact(F.array(two, one, label)).alias("patterns"))


def _outside(spans: DataFrame) -> DataFrame:
    """Base spans, and those candidates that no base span overlaps."""
    base = F.col("kind") < 4
    order = W.partitionBy("key").orderBy("start", "end", "kind")
    before = F.max(F.when(base, F.col("end"))).over(order.rowsBetween(W.unboundedPreceding, -1))
    after = F.min(F.when(base, F.col("start"))).over(order.rowsBetween(1, W.unboundedFollowing))
    out = spans.withColumn("hit", (F.coalesce(before, F.lit(-1)) > F.col("start")) | (F.coalesce(after, F.col("end")) < F.col("end")))
    return out.filter(base | ~F.col("hit")).drop("hit")


def secret(instance: str, long: int) -> str:
    """SQL: whether a token is shaped like a secret."""
    run = f"regexp_extract({instance}, '[a-z0-9+/_-]{{{long},}}', 0)"
    return f"(length(regexp_replace({run}, '[^0-9]', '')) >= 4 and length(regexp_replace({run}, '[^a-z]', '')) >= 4)"


def find(docs: DataFrame, rounds: int = 3, support: int = 3, confident: float = 0.75, least: int = 6, long: int = 20) -> DataFrame:
    """docs(key, t) to spans(key, kind, start, end): base spans (kind 0 to 3 in the order of KINDS) and discovered ones (4)."""
    keep = Kept(docs.sparkSession)
    spans = keep.keep(_outside(_matches(docs, least)))
    edges = keep.keep(spans.select("kind", "instance", F.explode("patterns").alias("pattern")).groupBy("pattern", "instance").agg(F.min("kind").alias("kind")))
    scores = edges.select("instance", F.expr(f"kind < 4 or {secret('instance', long)}").cast("double").alias("score")).groupBy("instance").agg(F.max("score").alias("score"))
    seeds = keep.keep(scores)
    scores = seeds
    for _ in range(rounds):
        per = edges.join(scores, "instance").groupBy("pattern").agg(F.sum("score").alias("s"), F.count("*").alias("n"), F.sum((F.col("score") >= 0.5).cast("int")).alias("k"))
        conf = keep.keep(per.filter(F.col("k") >= support).select("pattern", (F.col("s") / (F.col("n") + 1)).alias("conf")))
        new = edges.join(conf, "pattern").groupBy("instance").agg((1 - F.exp(F.sum(F.log(1 - F.col("conf"))))).alias("new"))
        scores = keep.keep(seeds.join(new, "instance", "left").select("instance", F.greatest("score", F.coalesce("new", F.lit(0.0))).alias("score")))
    cand = spans.filter("kind = 4").select("key", "kind", "start", "end", F.explode("patterns").alias("pattern"))
    more = cand.join(conf.filter(F.col("conf") >= confident), "pattern").select("key", "kind", "start", "end").distinct()
    return spans.filter("kind < 4").select("key", "kind", "start", "end").union(more)


def _keyed(docs: DataFrame) -> DataFrame:
    return docs.withColumn("t", F.coalesce("text", F.lit(""))).withColumn("key", F.xxhash64("doc_id", "t"))


def op9_bootstrapped_context(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _keyed(table(spark, sf_dir, "documents").select("doc_id", "text"))
    names = F.array(*map(F.lit, KINDS))
    spans = find(docs.select("key", "t")).withColumn("x", F.struct("start", "kind", F.concat_ws(":", names[F.col("kind")], "start", "end").alias("said")))
    counts = [F.count(F.when(F.col("kind") == k, 1)).alias(f"n_{kind}") for k, kind in enumerate(KINDS)]
    per = spans.groupBy("key").agg(*counts, F.array_sort(F.collect_list(F.when(F.col("kind") < 4, F.col("x")))).alias("base"), F.array_sort(F.collect_list("x")).alias("every"))
    per = per.select("key", *(f"n_{k}" for k in KINDS), F.concat_ws(",", "base.said").alias("base"), F.concat_ws(",", "every.said").alias("spans"))
    out = docs.select("doc_id", "key").join(per, "key", "left")
    zero = [F.coalesce(f"n_{k}", F.lit(0).cast("long")).alias(f"n_{k}") for k in KINDS]
    return out.select("doc_id", *zero[:4], F.sha2(F.coalesce("base", F.lit("")), 256).alias("base_sha256"), F.coalesce("spans", F.lit("")).alias("spans"), zero[4], sum((F.coalesce(f"n_{k}", F.lit(0).cast("long")) for k in KINDS), F.lit(0).cast("long")).alias("n_spans"))


def mask(spark: SparkSession, docs: DataFrame, sf_dir: str | None = None, most: int = 100_000) -> DataFrame:
    """Pipeline stage: each span becomes its kind in angle brackets; n_chars, where there, follows. All documents and columns stay.

    Base spans are replaced in place, without a shuffle. Discovered spans are joined: broadcast up to `most` of them, else by key."""
    keep = Kept(spark)
    keyed = _keyed(docs.select("doc_id", "text"))
    more = keep.keep(find(keyed.select("key", "t")).filter("kind = 4").groupBy("key").agg(F.array_sort(F.collect_list(F.struct("start", "end"))).alias("__ids")).withColumnRenamed("key", "__found"))
    names = docs.columns
    out = docs.withColumn("__key", F.xxhash64("doc_id", F.coalesce("text", F.lit(""))))
    few = more.count() <= most
    out = out.join(F.broadcast(more) if few else more, F.col("__key") == F.col("__found"), "left")
    cut = "concat(array_join(transform(sequence(0, size(__ids) - 1), i -> concat(substring(text, int(if(i = 0, 0, __ids[i - 1].end)) + 1, int(__ids[i].start - if(i = 0, 0L, __ids[i - 1].end))), '<ID>')), ''), substring(text, int(__ids[size(__ids) - 1].end) + 1))"
    text = f"if(__ids is null, text, {cut})"
    out = out.withColumn("text", F.expr(text))
    for kind in KINDS[:4]:
        p = _quoted(PATTERNS[kind])
        joined = f"array_join(transform(arrays_zip(split(text, {p}, -1), regexp_extract_all(text, {p}, 0)), x -> concat(x.`0`, case when x.`1` is null then '' when {valid(kind, 'x.`1`')} then '<{kind.upper()}>' else x.`1` end)), '')"
        out = out.withColumn("text", F.expr(f"case when {_NEEDS[kind].replace('(t,', '(text,').replace('t rlike', 'text rlike')} then {joined} else text end"))
    if "n_chars" in names:
        out = out.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*names)
