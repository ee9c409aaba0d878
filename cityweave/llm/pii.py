"""Personal data: validated shapes as seeds, and lexical patterns bootstrapped from them.

Everything is DataFrame expressions. Four kinds of identifier are found by
shape and checked (address parts, check digits, digit counts). A fifth kind,
secrets, has no check that could tell it from any other code: long hexadecimal
strings are its seeds, but they are reported only where a learnt pattern says so.

Tokens that look like identifiers, but weren't found by shape, are candidates.
What stands around an identifier (one or two words before, two behind, or one on
each side, with the punctuation between) is a lexical pattern, for one coarse
shape of token. Patterns and instances form a bipartite graph.
Trust goes to and fro: a pattern is scored by how many of its distinct
instances are trusted and of one kind, an instance by the best pattern around
it; trusted instances support further patterns, until no pattern is added.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cityweave.scratch import Scratch

KINDS = ("email", "ip", "card", "phone")
#: Kinds of all spans: those found by shape, and what only patterns find.
ALL_KINDS = (*KINDS, "secret")
SECRET = len(KINDS)

# The four shapes. Possessive repeats and the guard in front leave the matches
# as they are and keep the search linear: a run of class characters is entered
# at its start, or where the match before has ended.
SHAPES = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}

# Whether a text can have a match at all.
HINTS: dict[str, Callable[[Column], Column]] = {
    "email": lambda t: F.contains(t, F.lit("@")),
    "ip": lambda t: t.rlike(r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]"),
    "card": lambda t: t.rlike(r"[0-9](?:[\x20-]?[0-9]){11}"),
    "phone": lambda t: t.rlike(r"\+[0-9]"),
}

# Candidates: addresses with the sign spelt out, groups of digits, and codes of letters and digits.
SPELT = r"[A-Za-z0-9._%+-]++\x20?+[\[({](?:at|AT|At)[\])}]\x20?+[A-Za-z0-9-]++(?:(?:\.|\x20?+[\[({](?:dot|DOT|Dot)[\])}]\x20?+)[A-Za-z0-9-]++)*+"
GROUPS = r"[+(]?+[0-9]++(?:[\x20().-]{1,2}[0-9]++)++(?![A-Za-z0-9_])"
CODE = r"(?=(?:[A-Za-z_+/=.:-]*+[0-9]){4})[A-Za-z0-9_]++(?:[+/=.:-][A-Za-z0-9_]++)*+"
CANDIDATE = rf"(?<![A-Za-z0-9_])(?:{SPELT}|{GROUPS}|{CODE})"
CANDIDATE_HINT = r"[0-9]|[\[({](?:at|AT|At)[\])}]"

#: Coarse shapes: a pattern holds for tokens of one of them.
MAIL, NUMBER, LETTERED = range(3)
KIND_SHAPE = (MAIL, NUMBER, NUMBER, NUMBER, LETTERED)

#: Seeds of secrets: what access tokens and digests look like alike.
SECRET_SEED = r"^[0-9a-f]{40}$"
# Words before a hexadecimal string that say it is a digest.
DIGESTS = ("blob", "build", "checksum", "commit", "digest", "etag", "hash", "md5", "rev", "revision", "sha", "sha1", "sha256", "tree")

#: Characters of the text around an identifier that patterns look at.
REACH = 80

#: Matches whose gaps are summed in one go; keeps sums over long lists near linear.
RUN = 256


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with value worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _total(numbers: Column) -> Column:
    return F.aggregate(numbers, F.lit(0), lambda a, b: a + b)


def located(text: Column, pattern: str, context: bool = False) -> Column:
    """Matches of a pattern, leftmost first and without overlap: array of (start, end, match[, before, after]) in code points.

    The pieces between matches give the positions; before and after are what
    the neighbouring pieces have next to a match.
    """
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.split(text, pattern, -1)
    sides = [F.transform(gaps, lambda x: F.right(x, F.lit(REACH))).alias("l"), F.transform(gaps, lambda x: F.left(x, F.lit(REACH))).alias("r")] if context else []
    pair = F.struct(found.alias("m"), F.transform(gaps, F.length).alias("g"), *sides)

    def place(p: Column) -> Column:
        steps = F.zip_with(p["m"], F.slice(p["g"], 1, F.size(p["m"])), lambda m, g: F.length(m) + g)
        return let(F.struct(p.alias("p"), steps.alias("w")), lambda q: let(F.struct(q.alias("q"), _bases(q["w"]).alias("b")), _spans))

    def _bases(steps: Column) -> Column:
        sums = F.transform(F.sequence(F.lit(0), F.floor((F.greatest(F.size(steps), F.lit(1)) - 1) / RUN).cast("int")), lambda c: _total(F.slice(steps, c * RUN + 1, F.lit(RUN))))
        return let(sums, lambda s: F.transform(F.sequence(F.lit(0), F.size(s) - 1), lambda c: _total(F.slice(s, F.lit(1), c))))

    def _spans(r: Column) -> Column:
        p, steps, base = r["q"]["p"], r["q"]["w"], r["b"]

        def span(m: Column, i: Column) -> Column:
            run = F.floor(i / RUN).cast("int")
            before = F.get(base, run) + _total(F.slice(steps, run * RUN + 1, i - run * RUN)) + F.get(p["g"], i)
            more = [F.get(p["l"], i).alias("before"), F.get(p["r"], i + 1).alias("after")] if context else []
            return F.struct(before.alias("start"), (before + F.length(m)).alias("end"), m.alias("match"), *more)

        return F.transform(p["m"], span)

    return let(pair, place)


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    def add(total: Column, k: Column) -> Column:
        d = F.substring(digits, F.length(digits) - k, F.lit(1)).cast("int")
        return total + F.when(k % 2 == 0, d).otherwise(2 * d - F.when(d > 4, 9).otherwise(0))

    return F.aggregate(F.sequence(F.lit(0), F.length(digits) - 1), F.lit(0), add) % 10 == 0


# A part of four digits or more without leading zeros is over 255.
CHECKS: dict[str, Callable[[Column], Column]] = {
    "email": lambda m: F.lit(True),
    "ip": lambda m: ~F.exists(F.split(m, r"\."), lambda x: (F.length(F.regexp_replace(x, "^0+", "")) > 3) | (F.right(x, F.lit(3)).cast("int") > 255)),
    "card": lambda m: let(_digits(m), lambda d: F.when(F.length(d).between(12, 19), _luhn(d)).otherwise(False)),
    "phone": lambda m: F.length(_digits(m)).between(9, 15),
}

# What an instance that a pattern finds must be, by kind.
PLAUSIBLE: tuple[Callable[[Column], Column], ...] = (
    CHECKS["email"],
    lambda m: m.rlike(r"^[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+$") & CHECKS["ip"](m),
    CHECKS["card"],
    lambda m: F.length(_digits(m)).between(7, 15),
    lambda m: F.length(m) >= 8,
)

SPAN = "array<struct<start:int,end:int,kind:int>>"
SEEN = "array<struct<start:int,kind:int,end:int,match:string,before:string,after:string>>"
CANDIDATES = "array<struct<start:int,end:int,match:string,before:string,after:string>>"


def seen(text: Column) -> Column:
    """Checked matches of all kinds with their text and surroundings, sorted by start, then kind as listed."""
    return F.array_sort(F.concat(*[_seed(text, k, kind) for k, kind in enumerate(KINDS)]))


def _seed(text: Column, k: int, kind: str) -> Column:
    checked = F.filter(located(text, SHAPES[kind], context=True), lambda s: CHECKS[kind](s["match"]))
    spans = F.transform(checked, lambda s: F.struct(s["start"].alias("start"), F.lit(k).alias("kind"), s["end"].alias("end"), s["match"].alias("match"), s["before"].alias("before"), s["after"].alias("after")))
    return F.when(HINTS[kind](text), spans.cast(SEEN)).otherwise(F.array().cast(SEEN))


def spans(found: Column) -> Column:
    return F.transform(found, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))


def in_order(spans: Column) -> Column:
    """By start, then kind, then end."""
    return F.transform(F.array_sort(F.transform(spans, lambda s: F.struct(s["start"], s["kind"], s["end"]))), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))


def rendered(spans: Column) -> Column:
    """kind:start:end, comma-joined."""
    names = F.array(*[F.lit(k) for k in ALL_KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))), ",")


def can_have_any(text: Column) -> Column:
    """Whether a text can have a span of any kind."""
    return F.coalesce(text.rlike(CANDIDATE_HINT) | HINTS["email"](text), F.lit(False))


def scanned(docs: DataFrame) -> DataFrame:
    """(row, doc_id, key, seen, candidates) for each row of docs; null text counts as empty, key is a digest of the text."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    found = located(F.col("text"), CANDIDATE, context=True).cast(CANDIDATES)
    candidates = F.when(F.col("text").rlike(CANDIDATE_HINT), found).otherwise(F.array().cast(CANDIDATES))
    return rows.select("row", "doc_id", F.when(can_have_any(F.col("text")), F.sha2("text", 256)).alias("key"), seen(F.col("text")).alias("seen"), candidates.alias("candidates"))


def surroundings(before: Column, after: Column) -> Column:
    """Lexical patterns around an identifier: array of (form, context), without empty ones."""
    word, other = r"[\p{L}\p{N}_]", r"[^\p{L}\p{N}_]"
    plain = lambda c: F.lower(F.regexp_replace(c, r"\s+", " "))
    take = lambda c, pattern: F.regexp_extract(c, pattern, 0)

    def forms(sides: Column) -> Column:
        near, behind = take(sides["b"], rf"{word}+{other}*$"), take(sides["a"], rf"^{other}*{word}+")
        both = F.when((near != "") & (behind != ""), F.concat_ws("\t", near, behind)).otherwise(F.lit(""))
        all_ = (near, take(sides["b"], rf"{word}+{other}+{word}+{other}*$"), take(sides["a"], rf"^{other}*{word}+{other}+{word}+"), both)
        return F.array(*[F.struct(F.lit(k).alias("form"), c.alias("context")) for k, c in enumerate(all_)])

    named = let(F.struct(plain(before).alias("b"), plain(after).alias("a")), forms)
    return F.filter(named, lambda p: p["context"] != "")


def _shape(match: Column) -> Column:
    return F.when(match.rlike(r"[\[({@]"), F.when(match.rlike("[A-Za-z]"), MAIL).otherwise(NUMBER)).when(match.rlike("[A-Za-z_]"), LETTERED).otherwise(NUMBER)


def _by_kind(kind: Column, match: Column) -> Column:
    """Whether an instance can be of a kind at all."""
    out = F.lit(False)
    for k, check in enumerate(PLAUSIBLE):
        out = F.when(kind == k, (_shape(match) == KIND_SHAPE[k]) & check(match)).otherwise(out)
    return out


def lower_bound(trusted: Column, n: Column, z: float = 1.64) -> Column:
    """Wilson's lower confidence bound of a share."""
    p = F.least(trusted / n, F.lit(1.0))
    return (p + z * z / (2 * n) - z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)


def trusted_patterns(found: DataFrame, scratch: Scratch, rounds: int, trust: float, support: int) -> DataFrame:
    """(form, context, shape, kind, score) of the patterns that are trusted.

    found: (form, context, shape, match, kind) of seeds and candidates; kind is
    null for candidates. The graph has one edge for each distinct pattern and
    instance, however often they come together. A pattern's score is the lower
    bound of the share of its instances that are trusted to be of its kind; an
    instance that isn't a seed has the score and kind of the best trusted
    pattern around it. Rounds end when no pattern is added, or at `rounds`.
    """
    pattern = ["form", "context", "shape"]
    graph = scratch.keep(found.groupBy(*pattern, "match").agg(F.min("kind").alias("kind")))
    seeds = scratch.keep(graph.groupBy("match").agg(F.min("kind").alias("kind")).where("kind is not null").select("match", "kind", F.lit(1.0).alias("trust")))
    known, before, scored = seeds, -1, None
    for _ in range(rounds):
        told = graph.select(*pattern, "match").join(known, "match", "left")
        votes = told.groupBy(*pattern, "kind").agg(F.count("*").alias("n"), F.sum((F.col("trust") >= trust).cast("double")).alias("trusted"))
        best = votes.groupBy(*pattern).agg(F.sum("n").alias("n"), F.max(F.struct(F.coalesce("trusted", F.lit(0.0)).alias("trusted"), (-F.col("kind")).alias("less"))).alias("top"))
        ranked = best.select(*pattern, (-F.col("top.less")).alias("kind"), lower_bound(F.col("top.trusted"), F.col("n").cast("double")).alias("score"), F.col("top.trusted").alias("trusted"))
        old = scored
        scored = scratch.keep(ranked.where((F.col("trusted") >= support) & (F.col("score") >= trust)).drop("trusted"))
        if old is not None:
            scratch.remove(old)
        now = scored.count()
        if now == before:
            break
        before = now
        heard = graph.where("kind is null").join(scored.withColumnRenamed("kind", "of"), pattern).where(_by_kind(F.col("of"), F.col("match")))
        fresh = heard.groupBy("match").agg(F.max(F.struct("score", (-F.col("of")).alias("less"))).alias("top")).select("match", (-F.col("top.less")).alias("kind"), F.col("top.score").alias("trust"))
        grown = scratch.keep(seeds.unionByName(fresh.join(seeds, "match", "left_anti")))
        if known is not seeds:
            scratch.remove(known)
        known = grown
    scratch.remove(graph)
    return scored


def _found(docs: DataFrame, scratch: Scratch, rounds: int, trust: float, support: int) -> DataFrame:
    """(row, doc_id, key, base, added) for each row of docs."""
    rows = scratch.keep(scanned(docs))
    # candidates that touch a seed are what the seed is about
    each = rows.where(F.size("candidates") > 0).select("row", "seen", F.explode("candidates").alias("c")).where(~F.exists("seen", lambda s: (s["start"] < F.col("c.end")) & (s["end"] > F.col("c.start"))))
    digest = F.regexp_extract(F.coalesce(F.lower("c.before"), F.lit("")), r"([a-z0-9]+)[^\p{L}\p{N}]*$", 1).isin(*DIGESTS)
    fresh = each.where(F.length(F.regexp_replace("c.match", "[^0-9]", "")).between(4, 400) | (_shape(F.col("c.match")) == MAIL)).where(~digest)
    fresh = fresh.select("row", F.col("c.start").alias("start"), F.col("c.end").alias("end"), F.col("c.match").alias("match"), _shape(F.col("c.match")).alias("shape"), surroundings(F.col("c.before"), F.col("c.after")).alias("around"))
    fresh = scratch.keep(fresh)
    shape_of = F.array(*[F.lit(k) for k in KIND_SHAPE])
    known = rows.where(F.size("seen") > 0).select(F.explode("seen").alias("s")).select(F.col("s.match").alias("match"), F.get(shape_of, F.col("s.kind")).alias("shape"), F.col("s.kind").alias("kind"), F.explode(surroundings(F.col("s.before"), F.col("s.after"))).alias("p"))
    weak = F.when(F.col("match").rlike(SECRET_SEED), F.lit(SECRET))
    others = fresh.select("match", "shape", weak.alias("kind"), F.explode("around").alias("p"))
    patterns = trusted_patterns(known.unionByName(others).select("p.form", "p.context", "shape", "match", "kind"), scratch, rounds, trust, support)
    told = fresh.select("row", "start", "end", "match", "shape", F.explode("around").alias("p")).select("row", "start", "end", "match", "shape", "p.form", "p.context")
    new = told.join(patterns, ["form", "context", "shape"]).where(_by_kind(F.col("kind"), F.col("match")))
    each_best = new.groupBy("row", "start", "end").agg((-F.max(F.struct("score", (-F.col("kind")).alias("less")))["less"]).alias("kind"))
    # a row's own spans only, however many; nothing else comes together here
    added = each_best.groupBy("row").agg(F.collect_list(F.struct("start", "end", "kind")).alias("added"))
    return rows.select("row", "doc_id", "key", spans(F.col("seen")).alias("base")).join(added, "row", "left").select("row", "doc_id", "key", "base", in_order(F.coalesce(F.col("added").cast(SPAN), F.array().cast(SPAN))).alias("added"))


def personal_data(docs: DataFrame, rounds: int = 10, trust: float = 0.6, support: int = 5) -> DataFrame:
    """(row, doc_id, base, added): spans in code points of each row's text, end exclusive.

    base has the four kinds found by shape; added has what bootstrapped
    patterns find besides, without overlap with base. A pattern needs `support`
    trusted instances of one kind and a score of `trust` (see
    trusted_patterns). Null and empty texts have none; repeated rows give
    repeated results; `row` tells them apart.
    """
    return _found(docs, Scratch(docs.sparkSession, "pii"), rounds, trust, support).select("row", "doc_id", "base", "added")


def redacted(text: Column, spans: Column) -> Column:
    """text with each span replaced by its kind in angle brackets; overlapping spans count as one."""
    names = F.array(*[F.lit(f"<{k.upper()}>") for k in ALL_KINDS])
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        fresh = F.array(F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), F.get(names, s["kind"]))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.when(s["start"] >= acc["at"], F.concat(acc["out"], fresh)).otherwise(acc["out"]).alias("out"))

    return F.aggregate(spans, start, step, lambda acc: F.concat(F.array_join(acc["out"], ""), F.substring(text, acc["at"] + 1, F.length(text))))


def redact(docs: DataFrame, rounds: int = 10, trust: float = 0.6, support: int = 5) -> DataFrame:
    """docs, in its own columns, with personal data in text replaced; n_chars follows where there is one.

    Spans depend on a text alone once patterns are learnt, so they come back
    by a digest of the text: repeated ids, null ids and repeated rows don't
    matter. Null texts stay null.
    """
    found = _found(docs.select("doc_id", "text"), Scratch(docs.sparkSession, "pii"), rounds, trust, support)
    found = found.select("key", in_order(F.concat("base", "added")).alias("spans")).where(F.size("spans") > 0)
    key, mark, clean = unused(docs, "key"), unused(docs, "spans"), unused(docs, "clean")
    found = found.groupBy(F.col("key").alias(key)).agg(F.any_value("spans").alias(mark))
    may = can_have_any(F.col("text").cast("string"))
    joined = docs.where(may).withColumn(key, F.sha2(F.col("text").cast("string"), 256)).join(found, key, "left")
    done = joined.withColumn(clean, F.when(F.size(F.coalesce(F.col(mark), F.array().cast(SPAN))) > 0, redacted(F.col("text").cast("string"), F.col(mark))).otherwise(F.col("text")))
    same = lambda c: F.col(f"`{c}`")
    out = [F.col(clean).alias(c) if c == "text" else F.coalesce(F.when(F.col(mark).isNotNull(), F.length(clean)).cast(docs.schema[c].dataType), same(c)).alias(c) if c == "n_chars" else same(c) for c in docs.columns]
    return done.select(*out).unionByName(docs.where(~may))


def unused(df: DataFrame, name: str) -> str:
    """A column name that df lacks, made from name."""
    have = {c.lower() for c in df.columns}
    while name in have:
        name += "_"
    return name
