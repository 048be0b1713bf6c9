"""Personal data and information-theoretic sanitisation, in DataFrame functions only.

Personal data found by pattern are the protected entities. Terms around them are weighed by corpus
co-occurrence: a term's disclosure is its pointwise mutual information with the entity over the
entity's own information, 1 when the term gives the entity away and 0 when it says nothing.
A value of one or two texts has no counts to weigh by, so an entity is weighed at three levels: as
its value, as its group (domain, network, issuer, number range) and as its kind. Terms of enough
support over the threshold at some level are spans too: in every text of the corpus they are
removed, or generalised to their shape if they hold digits. All counts are of different texts.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

from .bitfilter import MAX_BITS, text_key
from .store import materialize

#: Each kind's cheap gate and its pattern. Possessive and anchored forms of the plain ones: the same
#: leftmost matches, in linear time and without recursion on long runs.
LOCAL = "[A-Za-z0-9._%+-]"
KINDS = {
    "email": (r"@[A-Za-z0-9-]++\.", rf"(?:\G|(?<!{LOCAL})){LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"),
    "ip": (r"[0-9]\.[0-9]++\.[0-9]++\.[0-9]", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"),
    "card": (r"[0-9](?:[ -]?[0-9]){15}", r"(?=(?:[0-9][ -]?){15}[0-9])[0-9]++(?:[ -][0-9]++)*+"),
    "phone": (r"\+[0-9]", r"\+[0-9][ ().0-9-]+[0-9]"),
}
SPANS = "array<struct<start:int,end:int,value:string>>"
WORD = r"[\p{L}\p{N}]"
RUN, BLOCK = 256, 12  # items of one fold; bits of the code points in one piece of a text
MOST = (1 << 31) - 1


@dataclass(frozen=True)
class DisclosureLimits:
    """context: characters on either side of an entity; support: different texts that must show the pair; threshold: of disclosure."""

    context: int = 80
    support: int = 3
    threshold: float = 0.9
    min_letters: int = 4


def let(value: Column, use: Callable[[Column], Column]) -> Column:
    """use(value), with value worked out once although use may name it in inner functions."""
    return F.transform(F.array(value), use)[0]


def before(items: Column, value: Callable[[Column], Column], fold: Callable[[Column, Column], Column], zero: int) -> Column:
    """For each item the fold of the values of all items before it; zero is neutral to fold.

    Folds run inside runs of RUN items, then over the runs: arrays grow by copies, so one fold over all would cost the square.
    """
    first = F.struct(F.lit(zero).alias("at"), F.array().cast("array<int>").alias("out"))
    run = lambda part: F.aggregate(part, first, lambda a, x: F.struct(fold(a["at"], value(x)).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")))
    starts = lambda xs: F.sequence(F.lit(1), F.greatest(F.size(xs), F.lit(1)), F.lit(RUN))
    runs = let(items, lambda xs: F.transform(starts(xs), lambda i: run(F.slice(xs, i, F.lit(RUN)))))
    heads = lambda rs: F.aggregate(rs, F.array(F.lit(zero)), lambda a, r: F.concat(a, F.array(fold(F.element_at(a, -1), r["at"]))))
    shifted = lambda rs, hs: F.flatten(F.transform(rs, lambda r, i: F.transform(r["out"], lambda x: fold(F.get(hs, i), x))))
    return let(runs, lambda rs: let(heads(rs), lambda hs: shifted(rs, hs)))


def matches(text: Column, pattern: Column) -> Column:
    """Leftmost matches with their code-point places, from the pieces between them."""
    found = F.regexp_extract_all(text, pattern, F.lit(0))
    pieces = F.split(text, pattern, -1)
    sized = let(found, lambda f: F.zip_with(F.slice(pieces, 1, F.size(f)), f, lambda gap, hit: F.struct(F.length(gap).alias("gap"), F.length(hit).alias("n"), hit.alias("hit"))))

    def place(x: Column, at: Column) -> Column:
        start = at + x["gap"]
        return F.struct(start.alias("start"), (start + x["n"]).alias("end"), x["hit"].alias("value"))

    return let(sized, lambda xs: F.zip_with(xs, before(xs, lambda x: x["gap"] + x["n"], lambda a, b: a + b, 0), place))


def outside(terms: Column, spans: Column) -> Column:
    """Those terms that overlap no span: in the order of all starts, no earlier span ends and no later one starts inside."""
    mark = lambda xs, base: F.transform(xs, lambda s: F.struct(s["start"], s["end"], F.lit(base).alias("base"), s["value"]))
    last = lambda xs: before(xs, lambda x: F.when(x["base"], x["end"]).otherwise(0), F.greatest, 0)
    following = lambda xs: F.reverse(before(F.reverse(xs), lambda x: F.when(x["base"], x["start"]).otherwise(MOST), F.least, MOST))
    places = let(F.array_sort(F.concat(mark(spans, True), mark(terms, False))), lambda xs: F.arrays_zip(xs.alias("x"), last(xs).alias("last"), following(xs).alias("next")))
    free = F.filter(places, lambda p: ~p["x"]["base"] & (p["last"] <= p["x"]["start"]) & (p["next"] >= p["x"]["end"]))
    return F.transform(free, lambda p: F.struct(p["x"]["start"].alias("start"), p["x"]["end"].alias("end"), p["x"]["value"].alias("value")))


def text_blocks(text: Column) -> Column:
    """The text in pieces of 1 << BLOCK code points."""
    return F.regexp_extract_all(text, F.lit(rf"(?s).{{1,{1 << BLOCK}}}"), F.lit(0))


def between(blocks: Column, start: Column, end: Column) -> Column:
    """The text from start to end, taken from its text_blocks: nothing is sought from the text's start."""
    i, j = F.shiftright(start, BLOCK), F.shiftright(end, BLOCK)
    skip = start - F.shiftleft(i, BLOCK) + 1
    near = F.substring(F.get(blocks, i), skip, end - start)
    far = F.concat(F.substring(F.get(blocks, i), skip, F.lit(1 << BLOCK)), F.array_join(F.slice(blocks, i + 2, j - i - 1), ""), F.coalesce(F.substring(F.get(blocks, j), F.lit(1), end - F.shiftleft(j, BLOCK)), F.lit("")))
    return F.when(start >= end, "").when(i == j, near).otherwise(far)


def luhn(digits: Column) -> Column:
    def part(i: Column) -> Column:
        d = F.substring(F.reverse(digits), i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return F.when(d > 9, d - 9).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), lambda a, i: a + part(i)) % 10 == 0


def valid(kind: str, value: Column) -> Column:
    digits = F.regexp_replace(value, "[^0-9]", "")
    if kind == "ip":
        part = "0*(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])"
        return value.rlike(rf"^{part}\.{part}\.{part}\.{part}$")
    if kind == "card":
        return F.length(digits).between(16, 19) & F.when(F.length(digits).between(16, 19), luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    return F.lit(True)


def base_spans(text: Column) -> dict[str, Column]:
    def of(kind: str, gate: str, pattern: str) -> Column:
        hits = F.filter(matches(text, F.lit(pattern)), lambda s: valid(kind, s["value"]))
        return F.when(text.rlike(gate), hits).otherwise(F.array().cast(SPANS))

    return {kind: of(kind, *rules) for kind, rules in KINDS.items()}


def with_kind(kind: str) -> Column:
    return F.transform(kind, lambda s: F.struct(F.lit(kind).alias("kind"), s["start"], s["end"], s["value"]))


def entities(kind: Column, value: Column) -> Column:
    """The keys of an entity, one for all spellings: its value, its group and its kind."""
    plain = F.when(kind == "email", F.lower(value)).otherwise(F.regexp_replace(value, r"[^0-9.]", ""))
    part = F.when(kind == "email", r"@.*$").when(kind == "ip", r"^[0-9]+\.[0-9]+\.[0-9]+\.").when(kind == "card", "^[0-9]{6}").otherwise("^[0-9]{4}")
    return F.array(F.xxhash64(kind, F.lit("value"), plain), F.xxhash64(kind, F.lit("group"), F.regexp_substr(plain, part)), F.xxhash64(kind, F.lit("kind")))


def around(found: DataFrame, limits: DisclosureLimits) -> DataFrame:
    """th, entity and terms near it: a row for each span and level of its entity."""
    pair = lambda bs, n: F.transform("spans", lambda s: F.struct(entities(s["kind"], s["value"]).alias("keys"), context_terms(bs, n, s["start"], s["end"], limits).alias("terms")))
    # contexts are cut before spans become rows, so no row carries its whole text
    each = let(text_blocks(F.col("text")), lambda bs: let(F.length("text"), lambda n: pair(bs, n)))
    near = found.select("th", F.explode(each).alias("s")).select("th", "s.keys", "s.terms")
    return near.select("th", F.explode("keys").alias("entity"), "terms")


def context_terms(blocks: Column, size: Column, start: Column, end: Column, limits: DisclosureLimits) -> Column:
    """Different whole terms near a span."""
    # one more character than the context shows whether it cuts a word
    reach = limits.context + 1
    prior = between(blocks, F.greatest(start - reach, F.lit(0)), start)
    after = between(blocks, end, F.least(end + reach, size))
    left = F.when(start > limits.context, F.regexp_replace(prior, rf"^{WORD}+", " ")).otherwise(prior)
    right = F.when(F.length(after) > limits.context, F.regexp_replace(after, rf"{WORD}+$", " ")).otherwise(after)
    whole = F.concat(left, F.lit(" "), right)
    terms = F.split(F.lower(whole), r"[^\p{L}\p{N}]+")
    return F.array_distinct(F.filter(terms, lambda t: F.length(t) >= limits.min_letters))


def words_of(terms: DataFrame, limits: DisclosureLimits) -> Column:
    """Different words of text whose hash bucket one of terms has: all of terms that it holds, and few others."""
    bucket = lambda t: F.pmod(F.xxhash64(t), F.lit(1 << 18)).cast("int")
    longs = {r[0]: r[1] for r in terms.select(bucket(F.col("term")).alias("b")).distinct().groupBy(F.shiftright("b", 6).alias("i")).agg(F.bit_or(F.expr("shiftleft(1L, b & 63)"))).collect()}
    table = F.from_json(F.lit(str([longs.get(i, 0) for i in range(1 << 12)])), "array<bigint>")
    wanted = lambda t: (F.length(t) >= limits.min_letters) & (F.getbit(F.element_at(table, F.shiftright(bucket(t), 6) + 1), bucket(t).bitwiseAND(63)) == 1)
    return F.array_distinct(F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), wanted))


def with_member(rows: DataFrame, key: str, of: DataFrame) -> DataFrame:
    """rows with member, true for every row whose 64-bit key is in of and for few others. The bitmap has 16 MB at most."""
    bits = min(MAX_BITS, max(15, (8 * of.count()).bit_length()))
    place = lambda k: F.col(k).bitwiseAND((1 << bits) - 1) + 1
    maps = of.select(place(key).alias("p")).groupBy(F.bitmap_bucket_number("p").alias("bucket_")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("p")).alias("map_"))
    at = F.bitmap_bit_position(place(key))
    byte = F.conv(F.hex(F.substring(F.col("map_"), (F.shiftright(at, 3) + 1).cast("int"), F.lit(1))), 16, 10).cast("bigint")
    member = F.coalesce(F.getbit(byte, at.bitwiseAND(7).cast("int")) == 1, F.lit(False))
    joined = rows.withColumn("bucket_", F.bitmap_bucket_number(place(key))).join(F.broadcast(maps), "bucket_", "left")
    return joined.withColumn("member", member).drop("bucket_", "map_")


def disclosing_terms(found: DataFrame, documents: DataFrame, limits: DisclosureLimits) -> DataFrame:
    """th and terms of every text that holds terms over the threshold; found: th, text and spans (kind, start, end, value)."""
    seen = around(found, limits)
    of_entity = seen.groupBy("entity").agg(F.countDistinct("th").alias("n_e")).where(F.col("n_e") >= limits.support)
    pairs = seen.select("entity", "th", F.explode("terms").alias("term")).distinct().groupBy("entity", "term").agg(F.count("*").alias("n_et")).where(F.col("n_et") >= limits.support)
    pairs = materialize(pairs.join(of_entity, "entity"), "pii-pairs")
    texts = documents.where(F.col("text").isNotNull()).select(text_key().alias("th"), "text")
    counts = materialize(texts.groupBy("th").agg(F.count("*").alias("n")), "pii-counts")
    # a text without copies is counted where it lies; only those that may have copies are gathered to count once
    words = with_member(texts, "th", counts.where("n > 1")).select("th", "member", words_of(pairs, limits).alias("words"))
    once = words.where("member").groupBy("th").agg(F.first("words").alias("words"))
    n_t = words.where("not member").select("words").unionByName(once.select("words")).select(F.explode("words").alias("term")).groupBy("term").agg(F.count("*").alias("n_t"))
    scored = pairs.join(n_t, "term").withColumn("n", F.lit(float(max(counts.count(), 1))))
    information = F.log(F.col("n") / F.least("n_e", "n"))
    mutual = F.log(F.col("n_et") * F.col("n") / (F.col("n_e") * F.greatest("n_t", "n_et")))
    terms = materialize(scored.where((information > 0) & (mutual / information >= limits.threshold)).select("term").distinct(), "pii-terms")
    if terms.isEmpty():  # no text needs another reading
        return terms.select(F.lit(0).cast("long").alias("th"), F.array("term").alias("terms"))
    held = texts.select("th", words_of(terms, limits).alias("words")).select("th", F.explode("words").alias("term"))
    return held.join(terms, "term").groupBy("th").agg(F.sort_array(F.collect_set("term")).alias("terms"))


def sanitise(documents: DataFrame, limits: DisclosureLimits = DisclosureLimits(), with_text: bool = True, keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: doc_id, columns of keep, an array of spans (start, end, value) for each kind and term, and the sanitised text.

    A null text is empty and has no spans; repeated rows give the same spans. Exact copies of a text count once in every
    number a term is weighed by. Terms that disclose an entity are spans in all texts, also far from it or without it.
    """
    carried = list(dict.fromkeys(("doc_id", *(k for k in keep if k != "text"))))
    source = documents.select(*(F.col(c).alias(f"c{i}_") for i, c in enumerate(carried)), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    held = [f"c{i}_" for i in range(len(carried))]
    spans = source.select(*held, "text", text_key().alias("th"), *(s.alias(k) for k, s in base_spans(F.col("text")).items()))
    some = sum((F.size(k) for k in KINDS), F.lit(0)) > 0
    first = materialize(spans.select(*held, "th", *KINDS, some.alias("some"), "text"), "pii-base")
    every = F.concat(*map(with_kind, KINDS))
    found = first.where("some").withColumn("spans", every)
    by_text = materialize(disclosing_terms(found.select("th", "text", "spans"), documents.select("text"), limits), "pii-texts")
    none = F.array().cast(SPANS)
    pattern = F.concat(F.lit(rf"(?iu)(?<!{WORD})(?:"), F.array_join("terms", "|"), F.lit(rf")(?!{WORD})"))
    term = F.when(F.col("terms").isNotNull(), outside(matches(F.col("text"), pattern), F.col("spans"))).otherwise(none)
    out = first.withColumn("spans", every).join(by_text, "th", "left").withColumn("term", term)
    columns = [*(F.col(h).alias(c) for h, c in zip(held, carried, strict=True)), *KINDS, "term"]
    return out.select(*columns, *([cleaned().alias("text")] if with_text else []))


def cleaned() -> Column:
    """Text with personal data replaced by the name of their kind; terms go, or keep only their shape if they hold digits."""
    marked = [F.transform(with_kind(k), lambda s: F.struct(s["start"], s["end"], F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")).alias("put"))) for k in KINDS]
    shape = lambda v: F.when(v.rlike("[0-9]"), F.regexp_replace(F.regexp_replace(v, r"\p{N}", "0"), r"\p{L}", "x")).otherwise("")
    terms = F.transform("term", lambda s: F.struct(s["start"], s["end"], shape(s["value"]).alias("put")))
    ordered = F.array_sort(F.concat(*marked, terms))
    some = sum((F.size(k) for k in (*KINDS, "term")), F.lit(0)) > 0

    def written(blocks: Column, xs: Column) -> Column:
        done = before(xs, lambda s: s["end"], F.greatest, 0)
        pieces = F.zip_with(xs, done, lambda s, at: F.when(s["start"] >= at, F.concat(between(blocks, at, s["start"]), s["put"])).otherwise(""))
        rest = between(blocks, F.array_max(F.transform(xs, lambda s: s["end"])), F.length("text"))
        return F.concat(F.array_join(pieces, ""), rest)

    return F.when(some, let(text_blocks(F.col("text")), lambda bs: let(ordered, lambda xs: written(bs, xs)))).otherwise(F.col("text"))


def listed(kinds: tuple[str, ...]) -> Column:
    """kind:start:end of every span, by kind and start, comma-joined."""
    parts = [F.transform(with_kind(k), lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))) for k in kinds]
    return F.array_join(F.concat(*parts), ",")
