"""Personal data: base patterns, and terms that reveal them by corpus co-occurrence.

DataFrame functions only. The base finds e-mail addresses, network addresses, payment cards and phone
numbers and checks them (octets, Luhn, digit counts). Every value found is a protected entity.

Information-theoretic part
    What is protected is each value, each kind of value, and any value at all. A term is a word of
    ``TERM_LETTERS`` letters or more outside the values. With p(e) the share of documents that hold e and
    p(e|t) that share among the documents with term t, the term tells PMI(e;t) = log2 p(e|t) / p(e) of the
    IC(e) = -log2 p(e) bits that e carries; what stays hidden is -log2 p(e|t). A term that tells at least
    ``TOLD_BITS`` is generalised to its class if it leaves at most ``GENERALISE_BITS`` hidden and removed
    if it leaves at most ``REMOVE_BITS``, wherever it stands.

    p(e|t) is estimated as (n(e,t) + SMOOTH p(e)) / (n(t) + SMOOTH), so that a word met a few times is no
    evidence. For a value, n(t) is the number of documents with t, and n(e,t) how many different contexts of
    ``CONTEXT`` characters on either side hold t beside e, or how many documents if those are fewer. For a
    kind (or any), documents are folded by their smallest value of the kind, since those that share it may
    be copies: n(e,t) counts the different ones, and n(t) those and the documents without any value. Values
    are compared in a normal form (digits of cards and phone numbers, lower case of addresses). All counts
    are over the whole corpus.

Plans
    Patterns are possessive and anchored by look-behind, so they run in linear time and constant stack.
    Positions come from the pieces between matches, inside one row. Frequencies are summed on the map side;
    the empty term stands for all documents in the same table. Revealing terms are put into one pattern if
    they are at most ``PATTERN_TERMS``; more are joined to the words of each text, by a broadcast up to
    ``BROADCAST_TERMS`` of them (a checked count) and by a shuffle beyond.

Defined cases
    Null text counts as empty and stays null when sanitised. Rows with a null doc_id are searched like
    others. Repeated rows are judged each. Empty tables give empty results. Other columns, whatever their
    names, are carried untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from discourselab.functions.text import let
from discourselab.llm.columns import unused
from discourselab.session import cut

CONTEXT = 64
TERM_LETTERS = 3
SMOOTH = 5
TOLD_BITS = 2.0
GENERALISE_BITS = 1.0
REMOVE_BITS = 0.15
PATTERN_TERMS = 200
BROADCAST_TERMS = 100_000

_LOCAL = "[A-Za-z0-9._%+-]"
#: Kinds in their fixed order, with the pattern of each.
PATTERNS = {
    "email": rf"(?:(?<!{_LOCAL})|\G){_LOCAL}++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?+[0-9]){13,18}+(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_HINT = {"email": "@", "phone": "+"}
_WORD = rf"(?<![\p{{L}}\p{{N}}])\p{{L}}{{{TERM_LETTERS},}}+(?!\p{{N}})"
_MATCHES = "array<struct<start:int,end:int,match:string,left:string,right:string>>"
_TERMS = "array<struct<start:int,end:int,match:string,bits:double>>"


def _digits(match: Column) -> Column:
    return F.regexp_replace(match, "[^0-9]", "")


def _luhn(match: Column) -> Column:
    backwards = F.reverse(_digits(match))

    def add(total: Column, at: Column) -> Column:
        digit = F.substring(backwards, at, F.lit(1)).cast("int")
        double = digit * 2
        return total + F.when(at % 2 == 1, digit).otherwise(double - F.when(double > 9, 9).otherwise(0))

    return F.aggregate(F.sequence(F.lit(1), F.length(backwards)), F.lit(0), add) % 10 == 0


def _valid(kind: str, match: Column) -> Column:
    if kind == "ip":
        return match.rlike(r"^(?:0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})(?:\.|$)){4}$")
    if kind == "card":
        return _luhn(match)
    if kind == "phone":
        return F.length(_digits(match)).between(10, 15)
    return F.lit(True)


def matches(text: Column, pattern: Column) -> Column:
    """array<struct<start, end, match, left, right>> of the leftmost non-overlapping matches; code points."""
    found, pieces = F.regexp_extract_all(text, pattern, F.lit(0)), F.split(text, pattern, -1)
    sides = let(pieces, lambda p: F.arrays_zip(F.slice(p, 1, F.size(p) - 1).alias("left"), F.slice(p, 2, F.size(p)).alias("right")))
    step = F.zip_with(found, sides, lambda m, s: F.struct(m.alias("match"), s["left"].alias("left"), s["right"].alias("right")))

    def walk(state: Column, x: Column) -> Column:
        start = state.pos + F.length(x["left"])
        end = start + F.length(x["match"])
        one = F.struct(start.alias("start"), end.alias("end"), x["match"].alias("match"), x["left"].alias("left"), x["right"].alias("right"))
        return F.struct(end.alias("pos"), F.concat(state.out, F.array(one)).alias("out"))

    start = F.struct(F.lit(0).alias("pos"), F.array().cast(_MATCHES).alias("out"))
    return F.when(F.size(found) > 0, F.aggregate(step, start, walk, lambda s: s.out)).otherwise(F.array().cast(_MATCHES))


def _base(text: Column, kind: str) -> Column:
    found = matches(text, F.lit(PATTERNS[kind]))
    if kind in _HINT:
        found = F.when(F.contains(text, F.lit(_HINT[kind])), found)
    found = F.filter(found, lambda m: _valid(kind, m["match"]))
    return F.coalesce(found, F.array().cast(_MATCHES))


def base_matches(text: Column) -> Column:
    """Struct of the base matches by kind."""
    return F.struct(*(_base(text, kind).alias(kind) for kind in PATTERNS))


def _normal(kind: str, match: Column) -> Column:
    return F.lower(match) if kind == "email" else match if kind == "ip" else _digits(match)


def _terms_of(text: Column) -> Column:
    return F.array_distinct(F.regexp_extract_all(F.lower(text), F.lit(_WORD), F.lit(0)))


def _replaced(text: Column, marks: Column) -> Column:
    """A text with marked stretches (start, end, label in order) replaced by their labels."""

    def walk(state: Column, m: Column) -> Column:
        kept = F.substring(text, state.pos + 1, F.greatest(m["start"] - state.pos, F.lit(0)))
        moved = F.struct(
            m["end"].alias("pos"),
            F.concat(state.parts, F.array(kept, F.when(m["start"] >= state.pos, m["label"]).otherwise(F.lit("")))).alias("parts"),
        )
        return F.when(m["end"] <= state.pos, state).otherwise(moved)

    first = F.struct(F.lit(0).alias("pos"), F.array().cast("array<string>").alias("parts"))
    rest = lambda s: F.concat(F.array_join(s.parts, ""), F.substring(text, s.pos + 1, F.length(text)))
    return F.when(F.size(marks) > 0, F.aggregate(marks, first, walk, rest)).otherwise(text)


def term_counts(docs: DataFrame) -> DataFrame:
    """(term, docs, units, n_any, n_<kind>...) of the terms that stand in a document with a value.

    The row of the empty term counts all documents. ``units`` is the number of documents after folding.
    """
    text = F.coalesce("text", F.lit(""))

    def kinds_of(pii: Column) -> Column:
        values = lambda k: F.transform(pii[k], lambda m: F.concat(F.lit(f"{k}:"), _normal(k, m["match"])))
        kinds = F.array(*(F.struct(F.lit(k).alias("kind"), F.array_min(values(k)).alias("rep")) for k in PATTERNS))
        return F.filter(kinds, lambda x: x["rep"].isNotNull())

    def words_of(pii: Column) -> Column:
        bare = let(_marks_of(pii, " "), lambda marks: _replaced(text, marks))
        return F.struct(kinds_of(pii).alias("kinds"), F.concat(F.array(F.lit("")), _terms_of(bare)).alias("terms"))

    words = docs.select(let(base_matches(text), words_of).alias("x")).select("x.kinds", F.explode("x.terms").alias("term"))
    either = F.array(F.struct(F.lit("any").alias("kind"), F.array_min(F.col("kinds.rep")).alias("rep")))
    none = F.array(F.struct(F.lit(None).cast("string").alias("kind"), F.lit(None).cast("string").alias("rep")))
    rows = words.select("term", F.inline(F.when(F.size("kinds") > 0, F.concat("kinds", either)).otherwise(none)))
    summed = rows.groupBy("term", "kind", "rep").agg(F.count("*").alias("n"))
    of = lambda k: F.count(F.when(F.col("kind") == k, 1))
    plain, held = F.sum(F.when(F.col("kind").isNull(), F.col("n")).otherwise(0)), F.sum(F.when(F.col("kind") == "any", F.col("n")).otherwise(0))
    counted = summed.groupBy("term").agg((plain + held).alias("docs"), (plain + of("any")).alias("units"), *(of(k).alias(f"n_{k}") for k in ("any", *PATTERNS)))
    return counted.where("n_any > 0 or term = ''")


def _likely(n: Column, prior: Column, total: Column) -> Column:
    """p(e|t), or null where the term does not tell enough of e."""
    p = F.least(F.lit(1.0), (n + SMOOTH * prior) / (total + SMOOTH))
    return F.when(p >= 2**TOLD_BITS * prior, p)


def revealing_terms(docs: DataFrame) -> DataFrame:
    """(term, hidden_bits) of the terms that leave at most ``GENERALISE_BITS`` of something protected hidden."""
    counts = cut(term_counts(docs))
    every = counts.where("term = ''").first()
    if every is None or not every.n_any:
        return counts.select("term", F.lit(0.0).alias("hidden_bits")).limit(0)
    terms = counts.where("term <> ''")
    best = F.greatest(*(_likely(F.col(f"n_{k}"), F.lit(every[f"n_{k}"] / every.units), F.col("units")) for k in ("any", *PATTERNS)))
    told = terms.select("term", best.alias("p"))

    based = docs.select(F.xxhash64("text").alias("doc"), F.coalesce("text", F.lit("")).alias("text")).select("doc", base_matches(F.col("text")).alias("pii"))
    named = lambda k: F.transform(F.col(f"pii.{k}"), lambda m: F.struct(F.concat(F.lit(f"{k}:"), _normal(k, m["match"])).alias("entity"), m["left"].alias("left"), m["right"].alias("right")))
    near = based.select("doc", F.explode(F.flatten(F.array(*map(named, PATTERNS)))).alias("x"))
    sides = F.concat(
        F.regexp_replace(F.right("x.left", F.lit(CONTEXT)), r"^[\p{L}\p{N}]+", ""),
        F.lit(" "),
        F.regexp_replace(F.left("x.right", F.lit(CONTEXT)), r"[\p{L}\p{N}]+$", ""),
    )
    near = cut(near.select("doc", F.xxhash64("x.entity").alias("entity"), sides.alias("context")))
    holders = near.groupBy("entity").agg(F.count_distinct("doc").alias("holders"))
    met = near.select("doc", "entity", F.xxhash64("context").alias("context"), F.explode(_terms_of(F.col("context"))).alias("term"))
    joint = met.groupBy("entity", "term").agg(F.least(F.count_distinct("context"), F.count_distinct("doc")).alias("n")).where("n > 1")
    values = joint.join(holders, "entity").join(terms.select("term", "docs"), "term")
    of_value = values.select("term", _likely(F.col("n"), F.col("holders") / every.docs, F.col("docs")).alias("p"))
    hidden = told.unionByName(of_value).groupBy("term").agg((-F.log2(F.max("p"))).alias("hidden_bits"))
    return cut(hidden.where(F.col("hidden_bits") <= GENERALISE_BITS))


def _pattern(terms: Column) -> Column:
    return F.concat(F.lit(r"(?iu)(?<![\p{L}\p{N}])(?:"), F.array_join(terms, "|"), F.lit(r")(?![\p{L}\p{N}])"))


def find(docs: DataFrame, base: str, held: str, pattern_terms: int = PATTERN_TERMS) -> DataFrame:
    """docs with the base matches by kind in column ``base`` and the matches of revealing terms in ``held``."""
    terms = revealing_terms(docs)
    n, text = terms.count(), F.coalesce("text", F.lit(""))
    out = docs.withColumn(base, base_matches(text))
    if not n:
        return out.withColumn(held, F.array().cast(_TERMS))
    marked = lambda bits, found: F.transform(found, lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end"), m["match"].alias("match"), F.element_at(bits, F.lower(m["match"])).alias("bits")))
    if n <= pattern_terms:
        rows = sorted((r.term, r.hidden_bits) for r in terms.collect())
        bits = F.create_map(*(F.lit(x) for row in rows for x in row))
        return out.withColumn(held, marked(bits, matches(text, _pattern(F.array(*(F.lit(t) for t, _ in rows))))))
    key, other, bits = unused(out, "key", "text_key", "bits")
    words = docs.select(F.xxhash64("text").alias(other), F.explode(_terms_of(text)).alias("term"))
    small = F.broadcast(terms) if n <= BROADCAST_TERMS else terms
    per_text = words.join(small, "term").groupBy(other).agg(F.map_from_entries(F.array_sort(F.collect_set(F.struct("term", "hidden_bits")))).alias(bits))
    joined = out.withColumn(key, F.xxhash64("text")).join(per_text, F.col(key) == F.col(other), "left")
    found = F.when(F.col(bits).isNotNull(), marked(F.col(bits), matches(text, _pattern(F.map_keys(bits)))))
    return joined.withColumn(held, F.coalesce(found, F.array().cast(_TERMS))).drop(key, other, bits)


def _marks_of(base: Column, label: str | None = None, terms: Column | None = None) -> Column:
    """All matches in order of place and kind, as (start, rank, end, kind, label)."""

    def marks(kind: str, rank: int, found: Column, shown: Column | None = None) -> Column:
        name = F.lit(f"[{kind.upper()}]" if label is None else label)
        return F.transform(
            found,
            lambda m: F.struct(
                m["start"].alias("start"),
                F.lit(rank).alias("rank"),
                m["end"].alias("end"),
                F.lit(kind).alias("kind"),
                (name if shown is None else _class_of(m)).alias("label"),
            ),
        )

    every = [marks(k, i, base[k]) for i, k in enumerate(PATTERNS)]
    return F.array_sort(F.concat(*every, *([] if terms is None else [marks("term", len(PATTERNS), terms, terms)])))


def _class_of(m: Column) -> Column:
    """What a term is generalised to; nothing if it is removed."""
    general = F.when(m["match"].rlike(r"^\p{Lu}"), F.lit("[NAME]")).otherwise(F.lit("[TERM]"))
    return F.when(m["bits"] <= REMOVE_BITS, F.lit("")).otherwise(general)


def _written(marks: Column) -> Column:
    return F.array_join(F.transform(marks, lambda m: F.concat_ws(":", m["kind"], m["start"].cast("string"), m["end"].cast("string"))), ",")


def spans(docs: DataFrame) -> DataFrame:
    """doc_id, counts by kind, the digest of the base spans and all spans of a (doc_id, text) table."""
    base, held = unused(docs, "pii", "terms")
    return find(docs, base, held).select(
        F.col("doc_id").cast("long").alias("doc_id"),
        *(F.size(F.col(base)[k]).cast("long").alias(f"n_{k}") for k in PATTERNS),
        F.sha2(_written(_marks_of(F.col(base))), 256).alias("base_sha256"),
        _written(_marks_of(F.col(base), terms=F.col(held))).alias("spans"),
    )


def sanitise(docs: DataFrame, pattern_terms: int = PATTERN_TERMS) -> DataFrame:
    """docs with every span replaced: base spans by their kind, terms by their class or by nothing."""
    base, held = unused(docs, "pii", "terms")
    marks = _marks_of(F.col(base), terms=F.col(held))
    return find(docs, base, held, pattern_terms).withColumn("text", _replaced(F.col("text"), marks)).select(*docs.columns)
