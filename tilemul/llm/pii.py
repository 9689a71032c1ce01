"""Personal data by fixed forms and by bootstrapped contextual extraction.

The four fixed forms give the base spans. Every base span is a seed, and so is a value that a cue
word such as ``password`` is set to. The words around a seed and its shape are lexical patterns;
patterns and the values seen in them make a bipartite graph. Round by round a pattern's confidence
comes from the values known so far, values gain scores from confident patterns, and values that
are accepted are seeds of the next round, until a round accepts nothing new.

Instances that can be discovered are what a form matched but its check refused, whitespace-free
tokens that are no plain words (they hold a digit, an @ or an underscore), and any token that a
colon or an equals sign precedes, letters only or not.

All of it is built of DataFrame functions. Spans are found from the pieces between matches:
their lengths, added up, are the places. Regular expressions are written so that no match is
tried twice from inside the same run and no group is repeated by recursion.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, hot_keys, join_hot, lower_ascii, whole

#: Kinds as listed; ``other`` is what patterns discover.
KINDS = ("email", "ip", "card", "phone", "other")
#: The forms, with possessive repetition and a start at the head of a run or
#: right after the match before, which leaves their leftmost matches as they are.
FORMS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for a form to give a span at all.
NEEDED = {
    "email": r"@[A-Za-z0-9-]",
    "ip": r"[0-9]\.[0-9]",
    "card": r"(?:[0-9][\x20-]?){11}[0-9]",
    "phone": r"\+[0-9]",
}
#: What ends a token besides white space: quotes, brackets and signs of punctuation.
_ENDS = r"\s\"'()\[\]{}<>|,;:=!?*#$%&"
#: Instances that are no matches of a form: tokens with a digit, an at sign or an underscore, and tokens
#: that something is set to. Possessive, so that a token is read once.
TOKEN = (
    rf"(?<![^{_ENDS}])[^{_ENDS}0-9@_]*+[0-9@_][^{_ENDS}]*+"
    rf"|(?<=[:=][ ]?[\"']?)(?<![^{_ENDS}])[^{_ENDS}]++"
)
NEEDED_TOKEN = r"[0-9@_:=]"
#: Words after which, and a colon or an equals sign, a value with a digit is a seed.
CUES = (
    "password", "passwd", "pwd", "secret", "token", "apikey", "api_key", "api-key", "access_key", "private_key",
    "bearer", "ssn", "passport", "iban",
)

#: Characters of a gap between matches that a context is read from; words beyond are no context.
BEFORE, AFTER = 64, 32
#: What an unknown value weighs against a known one, by the kind of pattern. Words around a value
#: say little, so an unknown value counts twice against them. A shape says much, and a check lets
#: only about a tenth of the values of a shape pass, so unknown ones hardly count.
UNKNOWN = {"<": 2.0, ">": 2.0, "=": 0.05}
#: A pattern counts where its confidence and its number of different known values reach these.
CONFIDENT, SUPPORT = 0.5, 5
#: A value is accepted at this score (1 minus the product of its patterns' doubts).
TAKEN = 0.5
#: Shapes of values shorter than this, or without a digit, are no patterns.
SHAPED = 8
#: Each round accepts at least one value; more rounds than this are an error, never a silent stop.
ROUNDS = 100
_BLOCK = 512


def _starts(gaps: Column, lengths: Column) -> Column:
    """Start of each match: gaps before it and matches before it, added up block by block."""
    gap, match = F.transform(gaps, F.length), lengths
    empty = F.expr("cast(array() as array<int>)")

    def block(acc: Column, b: Column) -> Column:
        def one(a: Column, i: Column) -> Column:
            start = a["at"] + F.get(gap, i)
            return F.struct(
                (start + F.get(match, i)).alias("at"), F.array_append(a["out"], start).alias("out")
            )

        first = b * _BLOCK
        last = F.least(first + (_BLOCK - 1), F.size(match) - 1)
        inner = F.aggregate(
            F.sequence(first, last), F.struct(acc["at"].alias("at"), empty.alias("out")), one
        )
        return F.get(
            F.transform(
                F.array(inner),
                lambda x: F.struct(x["at"].alias("at"), F.array_append(acc["outs"], x["out"]).alias("outs")),
            ),
            F.lit(0),
        )

    blocks = F.sequence(F.lit(0), F.floor((F.size(match) - 1) / _BLOCK).cast("int"))
    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<array<int>>)").alias("outs"))
    return F.flatten(F.aggregate(blocks, start, block)["outs"])


_MATCHES = "array<struct<start:int,end:int,value:string,before:string,after:string>>"
_SPANS = "array<struct<start:int,end:int,value:string>>"


def _let(value: Column, use) -> Column:
    """``use`` of a column that is computed once."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def matches(text: Column, pattern: str, needed: str) -> Column:
    """Leftmost non-overlapping matches as (start, end, value, before, after) in code points.

    ``before`` and ``after`` are what the gaps to the matches around hold, up to ``BEFORE`` and
    ``AFTER`` characters; gaps are cut out once, so that long texts take linear time.
    """
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.split(text, pattern, -1)

    def spans(f: Column) -> Column:
        both = F.struct(f.alias("values"), gaps.alias("gaps"), _starts(gaps, F.transform(f, F.length)).alias("starts"))
        return _let(
            both,
            lambda b: F.transform(
                F.arrays_zip(b["starts"].alias("s"), b["values"].alias("v"), b["gaps"].alias("g"), F.slice(b["gaps"], 2, F.size(b["values"])).alias("n")),
                lambda m: F.struct(
                    m["s"].alias("start"),
                    (m["s"] + F.length(m["v"])).alias("end"),
                    m["v"].alias("value"),
                    F.right(m["g"], F.lit(BEFORE)).alias("before"),
                    F.left(m["n"], F.lit(AFTER)).alias("after"),
                ),
            ),
        )

    none = F.expr(f"cast(array() as {_MATCHES})")
    some = _let(found, lambda f: F.when(F.size(f) > 0, F.slice(spans(f), 1, F.size(f))).otherwise(none))
    return F.when(text.rlike(needed), some).otherwise(none)


def _luhn(digits: Column) -> Column:
    """Whether a text of digits passes the check sum of card numbers."""

    def add(total: Column, i: Column) -> Column:
        digit = F.substring(digits, -i, F.lit(1)).cast("int")
        twice = digit * 2
        return total + F.when(i % 2 == 1, digit).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), add) % 10 == 0


def _passes(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        part = lambda p: F.regexp_replace(p, "^0+", "")
        return F.forall(
            F.split(value, r"\."), lambda p: (F.length(part(p)) <= 3) & (F.coalesce(part(p).try_cast("int"), F.lit(0)) <= 255)
        )
    if kind == "card":
        return F.length(digits).between(12, 19) & _luhn(digits)
    if kind == "phone":
        return F.length(digits).between(9, 15)
    return F.lit(True)


_CHECKED = "array<struct<start:int,end:int,value:string,before:string,after:string,ok:boolean>>"


def with_instances(docs: DataFrame) -> DataFrame:
    """(doc_id, content LONG, email, ip, card, phone, tokens): matches with contexts, texts left behind.

    ``content`` is a hash of the text. Matches of a form say by ``ok`` whether they pass its check.
    """
    text = F.col("text")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole().alias("text"))

    def checked(kind: str) -> Column:
        return F.transform(
            matches(text, FORMS[kind], NEEDED[kind]),
            lambda m: F.struct(*(m[c].alias(c) for c in ("start", "end", "value", "before", "after")), _passes(kind, m["value"]).alias("ok")),
        )

    forms = [checked(kind).alias(kind) for kind in FORMS]
    return rows.select("doc_id", F.xxhash64("text").alias("content"), *forms, matches(text, TOKEN, NEEDED_TOKEN).alias("tokens"))


def _shape(value: Column) -> Column:
    """Letters as a, digits as 9 with the length of each run; long mixed runs by their length."""
    lowered = lower_ascii(value)
    runs = F.regexp_replace(F.regexp_replace(lowered, "[a-z]+", "a"), "[0-9]", "9")
    mixed = lowered.rlike("^[0-9a-z]{16,}$") & lowered.rlike("[a-z]") & lowered.rlike("[0-9].*[0-9]")
    return F.when(mixed, F.concat(F.lit("x"), F.length(lowered).cast("string"))).otherwise(runs)


def _words(context: Column) -> Column:
    """A context lower-cased, digits as 9, quotes gone, signs of setting as words of their own."""
    plain = F.regexp_replace(F.regexp_replace(F.lower(context), "[0-9]", "9"), "[\"'`]", "")
    return F.filter(F.split(F.regexp_replace(plain, "([:=])", " $1 "), r"\s+"), lambda w: F.length(w) > 0)


def _patterns() -> Column:
    """Patterns of an instance: two words before, one word after, shape."""
    before, after, value = _words(F.col("before")), _words(F.col("after")), F.col("value")
    shaped = (F.length(value) >= SHAPED) & value.rlike("[0-9]")
    return F.array_compact(
        F.array(
            F.when(F.size(before) >= 2, F.concat(F.lit("<"), F.array_join(F.slice(before, -2, 2), " "))),
            F.when(F.size(after) > 0, F.concat(F.lit(">"), F.get(after, F.lit(0)))),
            F.when(shaped, F.concat(F.lit("="), _shape(value))),
        )
    )


def _cued() -> Column:
    """Whether a cue word and a sign of setting stand right before an instance with a digit."""
    cue = r"(?i)(?:^|[^a-z])(?:" + "|".join(CUES) + r")[\"']?\s?[:=]\s?[\"']?$"
    return F.col("before").rlike(cue) & F.col("value").rlike("[0-9]")


def instances(based: DataFrame) -> DataFrame:
    """(doc_id, content, start, end, value, seed, base, patterns) of every instance in ``based``.

    ``seed`` marks base spans and cued values, ``base`` the former. Nothing that touches a base span is
    an instance besides. A match that its form's check refused, though its number of digits fits,
    is one unless it lies inside a token; the tokens inside it are left to it.
    """
    fields = ("start", "end", "value", "before", "after")
    plain = lambda m, ok: F.struct(*(m[c].alias(c) for c in fields), ok.alias("ok"))
    of_forms = F.concat(*(F.col(k) for k in FORMS))
    passed = F.filter(of_forms, lambda m: m["ok"])
    touches = lambda spans, m: F.exists(spans, lambda b: (b["start"] < m["end"]) & (b["end"] > m["start"]))
    inside = lambda m, spans: F.exists(spans, lambda b: (b["start"] <= m["start"]) & (m["end"] <= b["end"]))
    digits = lambda m: F.length(F.regexp_replace(m["value"], "[^0-9]", ""))
    refused = F.concat(F.filter("card", lambda m: ~m["ok"] & digits(m).between(12, 19)), F.filter("ip", lambda m: ~m["ok"]))
    rows = based.where("size(tokens) > 0").select(
        "doc_id", "content", passed.alias("passed"), refused.alias("refused"), F.transform("tokens", lambda m: plain(m, F.lit(False))).alias("tokens")
    )
    free = lambda name: F.filter(name, lambda m: ~touches(F.col("passed"), m))
    rows = rows.select("doc_id", "content", "passed", free("refused").alias("refused"), free("tokens").alias("tokens"))
    rows = rows.withColumn("refused", F.filter("refused", lambda m: ~inside(m, F.col("tokens"))))
    rows = rows.withColumn("tokens", F.filter("tokens", lambda m: ~touches(F.col("refused"), m)))
    one = rows.select("doc_id", "content", F.explode(F.concat("passed", "refused", "tokens")).alias("m")).select(
        "doc_id", "content", *(F.col(f"m.{c}").alias(c) for c in fields), F.col("m.ok").alias("base")
    )
    # a value stands for all its spellings in upper and lower case
    return one.select(
        "doc_id", "content", "start", "end", lower_ascii(F.col("value")).alias("value"), (F.col("base") | _cued()).alias("seed"), "base", _patterns().alias("patterns")
    )


def discover(based: DataFrame) -> DataFrame:
    """(doc_id, content, start, end, value, score): values that confident patterns agree on, and cued ones.

    ``based``: rows of ``with_instances``. Base spans are not repeated here.
    """
    places = cut(instances(based).distinct())
    # pattern-value edges, summed up before anything is joined
    edges = cut(
        places.select("value", "seed", F.explode("patterns").alias("pattern"))
        .groupBy("pattern", "value")
        .agg(F.max("seed").alias("seed"))
    )
    scores = cut(places.groupBy("value").agg(F.max(F.when(F.col("seed"), 1.0).otherwise(0.0)).alias("score")))
    hot_patterns, hot_values = hot_keys(edges, "pattern"), hot_keys(edges, "value")
    edges = edges.select("pattern", "value")
    known = scores.where("score > 0").count()
    for _ in range(ROUNDS):
        scores = cut(_round(edges, scores, hot_patterns, hot_values))
        before, known = known, scores.where("score > 0").count()
        if known == before:
            break
    else:
        raise RuntimeError(f"patterns did not settle in {ROUNDS} rounds")
    found = scores.where("score > 0")
    hot = hot_keys(places, "value")
    return join_hot(places.where("not base"), found, "value", hot).select("doc_id", "content", "start", "end", "value", "score")


def _round(edges: DataFrame, scores: DataFrame, hot_patterns: DataFrame, hot_values: DataFrame) -> DataFrame:
    """Scores after one more round: known values stay known, others are accepted or stay at zero."""
    sums = (
        join_hot(edges, scores, "value", hot_values)
        .groupBy("pattern")
        .agg(F.sum("score").alias("weight"), F.count_if(F.col("score") > 0).alias("known"), F.count("*").alias("values"))
    )
    unknown = F.element_at(F.create_map(*(F.lit(x) for pair in UNKNOWN.items() for x in pair)), F.substring("pattern", 1, 1))
    confidence = F.col("weight") / (F.col("weight") + unknown * (F.col("values") - F.col("known")))
    patterns = sums.where(F.col("known") >= SUPPORT).withColumn("confidence", confidence).where(F.col("confidence") >= CONFIDENT)
    doubt = F.sum(F.log(F.greatest(1 - F.col("confidence"), F.lit(1e-9))))
    reached = (
        join_hot(edges, patterns.select("pattern", "confidence"), "pattern", hot_patterns)
        .groupBy("value")
        .agg((1 - F.exp(doubt)).alias("reached"))
        .where(F.col("reached") >= TAKEN)
    )
    gained = F.when(F.col("score") > 0, F.col("score")).otherwise(F.coalesce("reached", F.lit(0.0)))
    return scores.join(reached, "value", "left").select("value", gained.alias("score"))


def find(docs: DataFrame) -> DataFrame:
    """(doc_id, content, email, ip, card, phone, other, spans) for every row of ``docs``.

    Each kind has its matches (start, end, value); ``other`` are discovered values outside
    base spans; ``spans`` are all of them as (start, kind, end), in order. Null texts are
    empty, repeated rows each get a row, other columns are ignored, an empty table gives an
    empty result.
    """
    based = cut(with_instances(docs))
    other = (
        discover(based)
        .groupBy("doc_id", "content")
        .agg(F.array_sort(F.collect_set(F.struct("start", "end", "value"))).alias("other"))
        .select(F.col("doc_id").alias("found_id"), F.col("content").alias("found_content"), "other")
    )
    same = F.col("doc_id").eqNullSafe(F.col("found_id")) & (F.col("content") == F.col("found_content"))
    none = F.expr(f"cast(array() as {_SPANS})")
    span = lambda m: F.struct(*(m[c].alias(c) for c in ("start", "end", "value")))
    base = [F.transform(F.filter(k, lambda m: m["ok"]), span).alias(k) for k in FORMS]
    rows = based.join(other, same, "left").select("doc_id", "content", *base, F.coalesce("other", none).alias("other"))
    spans = F.array_sort(F.concat(*(_listed(k) for k in KINDS)))
    return rows.withColumn("spans", spans)


def _listed(kind: str) -> Column:
    n = KINDS.index(kind)
    return F.transform(
        kind, lambda m: F.struct(m["start"].alias("start"), F.lit(n).alias("kind"), m["end"].alias("end"))
    )


def spelled(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    names = F.array(*(F.lit(k) for k in KINDS))
    return F.array_join(
        F.transform(
            spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))
        ),
        ",",
    )


def report(docs: DataFrame) -> DataFrame:
    """(doc_id, n_email, n_ip, n_card, n_phone, n_other, n_spans, base_sha256, spans) for every row of ``docs``; see ``find``."""
    base = F.array_sort(F.concat(*(_listed(k) for k in FORMS)))
    return find(docs).select(
        "doc_id",
        *(F.size(k).cast("long").alias(f"n_{k}") for k in KINDS),
        F.size("spans").cast("long").alias("n_spans"),
        F.sha2(spelled(base), 256).alias("base_sha256"),
        spelled(F.col("spans")).alias("spans"),
    )


def masked(docs: DataFrame) -> DataFrame:
    """``docs`` with every span of personal data in ``text`` replaced by its kind in brackets.

    Spans that overlap are one, of the kind that starts first. ``n_chars``, where there is one,
    follows the text; all other columns and all rows stay as they are.
    """
    found = (
        find(docs)
        .where(F.size("spans") > 0)
        .groupBy("doc_id", "content")
        .agg(F.first("spans").alias("spans"))
        .select(F.col("doc_id").alias("found_id"), F.col("content").alias("found_content"), "spans")
    )
    boxed = docs.select(
        F.col("doc_id").cast("long").alias("id"), F.xxhash64(whole()).alias("content"), F.struct("*").alias("row")
    )
    names = F.array(*(F.lit(f"[{k.upper()}]") for k in KINDS))
    text = F.col("row.text")

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        piece = F.concat(
            F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.get(names, s["kind"])
        )
        return F.struct(
            F.greatest(acc["at"], s["end"]).alias("at"),
            F.when(fresh, F.array_append(acc["out"], piece)).otherwise(acc["out"]).alias("out"),
        )

    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<string>)").alias("out"))
    clean = _let(
        F.aggregate("spans", start, step),
        lambda a: F.concat(F.array_join(a["out"], ""), F.substring(text, a["at"] + 1, F.length(text))),
    )
    same = F.col("id").eqNullSafe(F.col("found_id")) & (F.col("content") == F.col("found_content"))
    joined = boxed.join(found, same, "left").select(
        "row", "spans", F.when(F.col("spans").isNotNull(), clean).otherwise(text).alias("clean")
    )
    fields = []
    for name in docs.columns:
        column = F.col(f"row.`{name}`")
        if name == "text":
            column = F.col("clean")
        elif name == "n_chars":
            column = F.when(F.col("spans").isNotNull(), F.length("clean")).otherwise(column).cast(docs.schema[name].dataType)
        fields.append(column.alias(name))
    return joined.select(*fields)
