"""Personal data by fixed patterns and by bootstrapped contextual extraction.

The fixed patterns find e-mail addresses, IP addresses, card numbers and telephone numbers (the base kinds).  Words that
have the form of a key or token (``SECRET``) are found by it as well, as kind ``other``.  All of these are the seeds of a
bootstrap: every seed span, of however many words, is one instance, and every other word that holds a digit or an at sign
and touches no base span is an instance that may turn out to be an identifier.  The context of an instance is the word of
the text before the word it starts in, in lower case and with every digit as 0 (a lexical pattern).

Patterns and instances form a graph.  A round gives each pattern a confidence, the sum of its distinct instances' scores
over one more than their number.  A pattern is trusted when it holds ``seeds`` distinct known instances and its confidence
reaches ``least``.  Each instance then has as score the chance that not all of the trusted patterns that hold it are wrong
(seeds keep the score 1), and is known from ``least`` on.  So what one round finds supports other patterns in the next, by
its other occurrences; scores only grow, and rounds end when no further pattern is trusted, or after ``rounds``.  Words in
the context of a trusted pattern are further identifiers, of kind ``other``, whatever their length.

All of it is DataFrame functions.  Positions are running sums of the lengths of what a pattern matches and of what lies
between, taken in chunks of ``CHUNK`` and chunks of chunks, so a text of a million matches is no problem; what touches
what is found by joining pieces of the text, not by looking through a list of spans for each word.  Patterns are written
so that the engine's matcher needs no recursion and no second look at a run of characters.

Defined results: null and empty texts have no spans; every row, also without ``doc_id`` or with one that others have too,
gives a row of its own; offsets are code points, end exclusive; what starts in the first word of a text has no context, and
neither has a match without any white space back to the second match before it; other columns are ignored; no rows give no
rows.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilesketch.llm.scratch import by_key, drop, keep

# fixed values: the patterns of the base kinds, in the order that breaks ties
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[ -]?[0-9])++",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
# fixed values: forms of keys and tokens (hexadecimal digests, access keys, web tokens)
SECRETS = (
    r"(?=[0-9]*+[A-Fa-f])[0-9A-Fa-f]{32,}+",
    r"AKIA[0-9A-Z]{16}",
    r"gh[a-z]_[A-Za-z0-9]{36,}+",
    r"sk[-_][A-Za-z0-9_-]{20,}+",
    r"eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]++\.[A-Za-z0-9_-]++",
)
SECRET = f"(?<![A-Za-z0-9])(?:{'|'.join(SECRETS)})(?![A-Za-z0-9])"
KINDS = [*PATTERNS, "other"]
CHUNK, PIECE = 64, 256
_WORD = r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D0-9@]*+[0-9@][^\x20\x09-\x0D]*+"
_SPANS = "array<struct<start:int,place:int,kind:string,end:int,value:string,left:string>>"


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use(value)`` with the value computed once."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _few_sums(x: Column) -> Column:
    """Running sums of a short array."""
    start = F.array(F.lit(0))
    return F.slice(F.aggregate(x, start, lambda out, v: F.concat(out, F.array(F.element_at(out, -1) + v))), F.lit(2), F.size(x))


def _chunked(x: Column, of_totals: Callable[[Column], Column]) -> Column:
    """Running sums: those of each chunk, and those of the chunks' totals before it."""
    n = F.ceil(F.size(x) / CHUNK).cast("int")
    chunks = F.transform(F.sequence(F.lit(0), n - 1), lambda c: _few_sums(F.slice(x, c * CHUNK + 1, F.lit(CHUNK))))

    def moved(sums: Column) -> Column:
        totals = F.transform(sums, lambda c: F.element_at(c, -1))
        shift = lambda base: lambda c, i: _let(F.coalesce(F.get(base, i - 1), F.lit(0)), lambda b: F.transform(c, lambda v: v + b))
        return _let(of_totals(totals), lambda base: F.flatten(F.transform(sums, shift(base))))

    return F.when(F.size(x) > 0, _let(chunks, moved)).otherwise(F.array().cast("array<int>"))


def running_sums(x: Column) -> Column:
    """Inclusive running sums of an array of integers, in two levels of chunks."""
    return _let(x, lambda v: _chunked(v, lambda totals: _chunked(totals, _few_sums)))


def _word_before(before: Column, inside: bool) -> Column:
    """The last word of a text, or with ``inside`` the last but the one that the text breaks off in.  Read from the end."""
    skip = r"^[^\x20\x09-\x0D]*+[\x20\x09-\x0D]++" if inside else r"^[\x20\x09-\x0D]*+"
    return F.reverse(F.regexp_extract(F.reverse(before), skip + r"([^\x20\x09-\x0D]++)", 1))


def located(text: Column, pattern: str, place: int, inside: bool) -> Column:
    """The matches as an array of spans; ``left`` is the word before the word that a match starts in."""

    def near(m: Column, b: Column, i: Column) -> Column:
        last = F.coalesce(F.get(m, i - 1), F.lit(""))
        close = F.nullif(_word_before(F.concat(last, F.get(b, i)), inside), F.lit(""))
        return F.coalesce(close, F.when(i > 0, _word_before(F.concat(F.get(b, i - 1), last, F.get(b, i)), inside)), F.lit(""))

    def spans(m: Column, b: Column, ends: Column) -> Column:
        fields = lambda x, i: (F.get(ends, i) - F.length(x), F.lit(place), F.lit(KINDS[place]), F.get(ends, i), x, near(m, b, i))
        return F.transform(m, lambda x, i: F.struct(*(v.alias(n) for v, n in zip(fields(x, i), ("start", "place", "kind", "end", "value", "left"), strict=True))))

    def between(m: Column) -> Column:
        steps = lambda b: F.transform(m, lambda x, i: F.length(F.get(b, i)) + F.length(x))
        return _let(F.split(text, pattern, -1), lambda b: _let(running_sums(steps(b)), lambda ends: spans(m, b, ends)))

    return _let(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda m: F.when(F.size(m) > 0, between(m)))


def _lexical(word: Column) -> Column:
    return F.regexp_replace(F.lower(word), "[0-9]", "0")


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    """Whether the check digit of a string of digits is right."""
    doubled = F.array(*(F.lit(x) for x in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)))
    single = F.filter(F.split(F.reverse(digits), ""), lambda d: d != "")
    worth = F.transform(single, lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise(F.element_at(doubled, d.cast("int") + 1)))
    return F.aggregate(worth, F.lit(0), lambda s, x: s + x) % 10 == 0


def _sound(kind: str, value: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.right(p, F.lit(9)).cast("int") <= 255))
    if kind == "card":
        return F.length(_digits(value)).between(14, 19) & _luhn(_digits(value))
    if kind == "phone":
        return F.length(_digits(value)).between(10, 15)
    return F.lit(True)


def _check(kind: str):
    return lambda x: _sound(kind, x["value"])


def base_spans(text: Column) -> Column:
    """The spans of the base kinds, sorted by start and then kind."""
    parts = []
    for place, (kind, pattern) in enumerate(PATTERNS.items()):
        possible = {"email": F.contains(text, F.lit("@")), "phone": F.contains(text, F.lit("+"))}.get(kind, F.lit(True))
        spans = F.when(possible, F.filter(located(text, pattern, place, True), _check(kind)))
        parts.append(F.coalesce(spans, F.array().cast(_SPANS)))
    return F.array_sort(F.concat(*parts))


def written(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"], x["end"])), ",")


def bootstrap(occurrences: DataFrame, rounds: int = 5, seeds: int = 3, least: float = 0.8) -> DataFrame:
    """The patterns to trust, from ``(pattern, instance, seed boolean)``."""
    graph = keep(occurrences.groupBy("pattern", "instance").agg(F.max(F.col("seed").cast("int")).alias("seed")))
    per = graph.groupBy("instance").agg(F.max("seed").alias("seed"), F.count(F.lit(1)).alias("c"))
    score = keep(per.withColumn("score", F.col("seed").cast("double")))
    pairs, trusted, made = graph.select("pattern", "instance"), -1, [graph, score]
    for _ in range(rounds):
        held = by_key(pairs, score.select("instance", "score", "c"), "instance").groupBy("pattern")
        held = held.agg(F.count(F.lit(1)).alias("c"), F.count_if(F.col("score") >= least).alias("known"), F.sum("score").alias("s"))
        held = held.withColumn("conf", F.col("s") / (F.col("c") + 1)).where((F.col("known") >= seeds) & (F.round("conf", 9) >= least))
        conf = keep(held.select("pattern", "c", "conf"))
        made.append(conf)
        before, trusted = trusted, conf.count()
        if trusted in (0, before):
            break
        right = F.log(1 - F.least(F.col("conf"), F.lit(0.999)))
        found = by_key(pairs, conf, "pattern").groupBy("instance").agg((1 - F.exp(F.sum(right))).alias("found"))
        value = F.when(F.col("seed") == 1, F.lit(1.0)).otherwise(F.greatest("score", F.coalesce("found", F.lit(0.0))))
        score = keep(score.join(found, "instance", "left").select("instance", "seed", "c", value.alias("score")))
        made.append(score)
    out = keep(conf.select("pattern"))
    drop(*made)
    return out


def _pieces(start: Column, end: Column) -> Column:
    """Numbers of the pieces of a text that a span touches."""
    return F.explode(F.sequence(F.floor(start / PIECE), F.floor((end - 1) / PIECE)))


def _apart(words: DataFrame, base: DataFrame) -> DataFrame:
    """The words ``(row, start, end, ...)`` that touch no span of ``base(row, from, to)``."""
    near = words.where("crowded").select("row", "start", "end", _pieces(F.col("start"), F.col("end")).alias("piece"))
    spans = base.select("row", "from", "to", _pieces(F.col("from"), F.col("to")).alias("piece"))
    met = near.join(spans, ["row", "piece"]).where("from < end and to > start").select("row", "start").distinct()
    return words.join(met, ["row", "start"], "left_anti")


def personal_data(docs: DataFrame, rounds: int = 5, seeds: int = 3, least: float = 0.8) -> DataFrame:
    """``doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_other, n_found`` of every row; ``n_found`` counts all
    spans."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    found = found.select("doc_id", base_spans(F.col("text")).alias("base"), located(F.col("text"), _WORD, 4, False).alias("words"))
    found = keep(found.withColumn("row", F.monotonically_increasing_id()))
    base = found.where(F.size("base") > 0).select("row", F.explode("base").alias("b")).select("row", "b.*")

    word = found.where(F.size("words") > 0).select("row", (F.size("base") > 0).alias("crowded"), F.explode("words").alias("w"))
    core = F.regexp_replace("w.value", r"^[^\p{L}0-9+]++|[^\p{L}0-9]++$", "")
    lead = F.length(F.regexp_extract("w.value", r"^[^\p{L}0-9+]*+", 0))
    secret = located(F.col("w.value"), SECRET, 4, True)
    whole = F.array(F.struct(lead.alias("start"), (lead + F.length(core)).alias("end"), core.alias("value"), F.lit(False).alias("seed")))
    keys = F.transform(secret, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), x["value"].alias("value"), F.lit(True).alias("seed")))
    word = word.select("row", "crowded", F.col("w.start").alias("at"), _lexical(F.col("w.left")).alias("pattern"), F.explode(F.coalesce(keys, whole)).alias("x"))
    word = word.select("row", "crowded", "pattern", (F.col("at") + F.col("x.start")).alias("start"), (F.col("at") + F.col("x.end")).alias("end"), F.col("x.value").alias("instance"), F.col("x.seed").alias("seed"))
    word = keep(_apart(word.where("instance <> ''"), base.select("row", F.col("start").alias("from"), F.col("end").alias("to"))))

    seed = base.select(_lexical(F.col("left")).alias("pattern"), F.col("value").alias("instance"), F.lit(True).alias("seed"))
    seen = seed.unionByName(word.select("pattern", "instance", "seed")).where("pattern <> ''")
    trusted = bootstrap(seen, rounds, seeds, least)
    known = word.where("seed").select("row", "start", "end").unionByName(word.join(trusted, "pattern", "left_semi").select("row", "start", "end"))
    span = F.struct(F.col("start"), F.lit(4).alias("place"), F.lit("other").alias("kind"), F.col("end"))
    more = known.groupBy("row").agg(F.collect_set(span).alias("more"))

    short = "array<struct<start:int,place:int,kind:string,end:int>>"
    plain = F.transform("base", lambda x: F.struct(*(x[n].alias(n) for n in ("start", "place", "kind", "end"))))
    both = found.select("row", "doc_id", plain.alias("base")).join(more, "row", "left").withColumn("more", F.coalesce("more", F.array().cast(short)))
    count = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    spans = written(F.array_sort(F.concat("base", "more")))
    return both.select("doc_id", *(count(k) for k in PATTERNS), F.sha2(written(F.col("base")), 256).alias("base_sha256"), spans.alias("spans"), F.size("more").cast("long").alias("n_other"), (F.size("base") + F.size("more")).cast("long").alias("n_found"))
