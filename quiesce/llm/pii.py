"""Personal data and what reveals it, in DataFrame functions only.

*Base spans* are the leftmost non-overlapping matches of four patterns that pass
their checks. A match's place follows from splitting the text by the same pattern:
the lengths of the pieces and of the matches before it. Patterns start at the head
of a run (or where the last match ended), which finds the same matches and never
tries the inside of a run again, so a text without white space costs no more.

*Information-theoretic sanitisation.* Protected entities are the different matched
values (an address, a number, whatever its spelling) and the four kinds, each in every
text that holds it. A term t (run of letters, outside addresses) reveals an entity e by
the pointwise mutual information  log(n_te N / (n_t n_e)),  document counts taken over
the whole corpus; it discloses e if that reaches ``alpha`` times the information
log(N / n_e) of e itself, on at least ``support`` different texts with both, and chance
does not explain it: were t dealt out over texts regardless of e, so many of the
different texts of e would hold it with a probability of at most exp(-d_e KL(d_te / d_e
|| n_t / N)), which has to stay below ``level`` over the number of terms of the corpus
(at most ``level`` terms of an entity are expected to pass by chance). d counts
different texts, so copies of one text are no evidence. In a text that holds e such
terms become spans of kind "term". The term is generalised to its first ``prefix``
letters if those disclose no entity of the text, by the same measure, and removed
otherwise. Texts without personal data never change.

Terms are counted under 63-bit hashes, so the shuffle carries numbers, combined in each
task first. The patterns read every text once, the counts once more; everything else
reads the few texts that hold personal data.

Defined results: null text is empty (and stays null in ``sanitise``); an empty table
gives an empty result; rows are told apart by a number of their own, so repeated and
null ids change nothing; overlapping spans of different kinds are all listed and
replaced once, from the first; extra columns are kept by ``sanitise`` and ignored by
``find_spans``, whatever their names.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stash, text_or_empty

_LOCAL = r"A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:(?<![{_LOCAL}])|\G)[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
KINDS = tuple(PATTERNS)
#: What a text must contain for a pattern to be tried.
_HINTS = {"email": "@", "ip": ".", "card": None, "phone": "+"}
_WORD = r"\p{L}\p{M}"
_BYTE = r"^0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])$"
SPAN = "array<struct<kind:string,start:int,end:int,m:string>>"
_STEP = 128
_CHUNK = 1024


def _luhn(digits: Column) -> Column:
    def value(i: Column) -> Column:
        d = F.substring(digits, -i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return F.when(i % 2 == 0, twice).otherwise(d)

    places = F.sequence(F.lit(1), F.length(digits))
    return F.aggregate(places, F.lit(0), lambda acc, i: acc + value(i)) % 10 == 0


def _passes(kind: str, m: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: p.rlike(_BYTE))
    if kind == "card":
        digits = F.regexp_replace(m, "[ -]", "")
        return F.when(F.length(digits).between(13, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(F.regexp_replace(m, "[^0-9]", "")).between(9, 15)
    return F.lit(True)


def _total(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda acc, x: acc + x)


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with the value worked out once for a row, however often the body reads it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def spans_of(kind: str, text: Column, pattern: Column) -> Column:
    """The checked spans of a pattern in a text, by position."""

    def placed(found: Column, gaps: Column, sums: Column) -> Column:
        # gaps[i]: from the end of match i - 1 to the start of match i, and match i - 1; sums: of _STEP gaps
        def span(m: Column, i: Column) -> Column:
            block = F.floor(i / _STEP).cast("int")
            start = _total(F.slice(sums, F.lit(1), block)) + _total(F.slice(gaps, block * _STEP + 1, i % _STEP + 1))
            return F.struct(F.lit(kind).alias("kind"), start.alias("start"), F.length(m).alias("n"), m.alias("m"))

        good = F.filter(F.transform(found, span), lambda s: _passes(kind, s["m"]))
        return F.transform(good, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), (s["start"] + s["n"]).alias("end"), s["m"].alias("m")))

    def with_gaps(found: Column, pieces: Column) -> Column:
        gaps = F.transform(found, lambda m, i: F.get(pieces, i) + F.when(i > 0, F.length(F.get(found, i - 1))).otherwise(0))
        return _let(gaps, lambda g: _let(_sums(g), lambda sums: placed(found, g, sums)))

    def with_pieces(found: Column) -> Column:
        pieces = F.transform(F.split(text, pattern, -1), lambda x: F.length(x))
        return F.when(F.size(found) > 0, _let(pieces, lambda p: with_gaps(found, p)))

    hint = _HINTS.get(kind)
    there = F.contains(text, F.lit(hint)) if hint else pattern.isNotNull()
    none = F.array().cast(SPAN)
    return F.coalesce(F.when(there, _let(F.regexp_extract_all(text, pattern, F.lit(0)), with_pieces)), none)


def _sums(values: Column) -> Column:
    blocks = F.sequence(F.lit(0), F.floor((F.size(values) - 1) / _STEP).cast("int"))
    return F.transform(blocks, lambda b: _total(F.slice(values, b * _STEP + 1, _STEP)))


def with_base(df: DataFrame) -> DataFrame:
    """Adds to a text ``t``: b (spans by kind), base (all of them, in the order of kinds) and mask (bit i: holds kind i)."""
    df = df.withColumn("b", F.struct(*(spans_of(k, F.col("t"), F.lit(p)).alias(k) for k, p in PATTERNS.items())))
    mask = reduce(lambda a, b: a + b, (F.when(F.size(f"b.{k}") > 0, 1 << i).otherwise(0) for i, k in enumerate(KINDS)))
    return df.withColumns({"base": F.concat(*(F.col(f"b.{k}") for k in KINDS)), "mask": mask})


def _terms(text: Column) -> Column:
    outside = F.when(F.contains(text, F.lit("@")), F.regexp_replace(text, PATTERNS["email"], " ")).otherwise(text)
    return F.array_distinct(F.split(F.lower(outside), f"[^{_WORD}]+"))


def _class_of(term: Column, prefix: int) -> Column:
    return F.substring(term, 1, prefix)


def _entities(spans: Column) -> Column:
    """Hashes of the kinds and of the different values among base spans."""
    value = lambda s: F.when(s["kind"].isin("card", "phone"), F.regexp_replace(s["m"], "[^0-9]", "")).otherwise(F.lower(s["m"]))
    return F.array_distinct(F.concat(F.transform(spans, lambda s: F.xxhash64(s["kind"])), F.transform(spans, lambda s: F.xxhash64(s["kind"], value(s)))))


def _word_key(word: Column) -> Column:
    return F.xxhash64(word).bitwiseAND(F.lit(-2))


def _head_key(word: Column, prefix: int) -> Column:
    """Keys of prefixes are odd and those of words even, so both are counted in one table."""
    return F.xxhash64(_class_of(word, prefix)).bitwiseOR(F.lit(1))


def _keys(terms: Column, prefix: int) -> Column:
    return _let(terms, lambda ws: F.concat(F.transform(ws, _word_key), F.array_distinct(F.transform(ws, lambda w: _head_key(w, prefix)))))


def disclosing(texts: DataFrame, private: DataFrame, alpha: float, support: int, level: float, prefix: int) -> DataFrame:
    """(e, h): entities and the keys of words and prefixes that disclose them.

    texts: every text as ``t``; private: t and base of those with base spans.
    """
    terms = F.array_remove(_terms(F.col("t")), "")
    shown = private.select(F.xxhash64("t").alias("x"), _entities(F.col("base")).alias("es"), _keys(terms, prefix).alias("hs"))
    # one row for each different text, with the number of its copies
    kinds = shown.groupBy("x").agg(F.count(F.lit(1)).alias("copies"), F.first("es").alias("es"), F.first("hs").alias("hs"))
    entities = kinds.select("copies", F.explode("es").alias("e")).groupBy("e").agg(F.count(F.lit(1)).alias("d_e"), F.sum("copies").alias("n_e")).filter(F.col("d_e") >= support)
    # an entity of fewer texts cannot be disclosed, so its pairs are not made
    kept = kinds.select("x", F.explode("es").alias("e")).join(entities.select("e"), "e", "left_semi").groupBy("x").agg(F.collect_list("e").alias("es"))
    pairs = kinds.drop("es").join(kept, "x").select("copies", "es", F.explode("hs").alias("h")).select("copies", F.explode("es").alias("e"), "h")
    pairs = pairs.groupBy("e", "h").agg(F.count(F.lit(1)).alias("d_te"), F.sum("copies").alias("n_te")).filter(F.col("d_te") >= support)
    # every text once: a row for each of its different words and prefixes, summed where it is made
    counts = stash(texts.select(F.explode(_keys(terms, prefix)).alias("h")).groupBy("h").agg(F.count(F.lit(1)).alias("n_t")))
    n = texts.count()
    odd = F.col("h").bitwiseAND(F.lit(1)) == 1
    heads, words = counts.agg(F.count(F.when(odd, 1)), F.count(F.when(~odd, 1))).first()
    every = pairs.join(entities, "e").join(counts, "h")
    v = F.when(odd, max(1, heads)).otherwise(max(1, words))
    share, usual = F.col("d_te") / F.col("d_e"), F.col("n_t") / F.lit(max(1, n))
    pmi = F.log(F.col("n_te") * F.lit(n) / (F.col("n_t") * F.col("n_e")))
    rest = F.when(share < 1, (1 - share) * F.log((1 - share) / (1 - usual))).otherwise(0.0)
    surprise = F.when(share > usual, F.col("d_e") * (share * F.log(share / usual) + rest)).otherwise(0.0)
    # an entity that every text holds has no information to protect
    tells = (F.col("n_e") < n) & (pmi >= alpha * F.log(F.lit(n) / F.col("n_e"))) & (surprise >= F.log(v / level))
    return every.filter(tells).select("e", "h")


_SALTS = 8


def disclosed_terms(private: DataFrame, told: DataFrame, prefix: int) -> DataFrame:
    """key, words: array of (w, put) that disclose an entity held by that row. private: key, t, base."""
    words = private.select("key", _entities(F.col("base")).alias("es"), F.explode(_terms(F.col("t"))).alias("w")).filter("w <> ''")
    of_term = told.filter(F.col("h").bitwiseAND(F.lit(1)) == 0).groupBy("h").agg(F.collect_set("e").alias("of"))
    # a word of very many texts meets what it tells on several tasks
    of_term = of_term.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(_SALTS - 1))))
    hits = words.withColumns({"h": _word_key(F.col("w")), "salt": F.pmod(F.xxhash64("key"), F.lit(_SALTS)).cast("int")}).join(of_term, ["h", "salt"]).filter(F.arrays_overlap("es", "of"))
    hits = hits.select("key", "w", _head_key(F.col("w"), prefix).alias("head"), F.explode("es").alias("e"))
    hits = hits.join(told.select("e", F.col("h").alias("head"), F.lit(1).alias("head_hit")), ["e", "head"], "left")
    hits = hits.groupBy("key", "w").agg(F.max("head_hit").alias("head_hit"))
    general = (F.length("w") > prefix + 1) & F.col("head_hit").isNull()
    put = F.when(general, F.concat(_class_of(F.col("w"), prefix), F.lit("*"))).otherwise("")
    return hits.groupBy("key").agg(F.sort_array(F.collect_set(F.struct("w", put.alias("put")))).alias("words"))


def _any_of(words: Column) -> Column:
    quoted = F.transform(words, lambda x: F.concat(F.lit(r"\Q"), x["w"], F.lit(r"\E")))
    return F.concat(F.lit(rf"(?<![{_WORD}])(?iu:"), F.array_join(quoted, "|"), F.lit(rf")(?![{_WORD}])"))


def protected(rows: DataFrame, alpha: float = 0.75, support: int = 2, level: float = 0.05, prefix: int = 4) -> DataFrame:
    """row, t, b, base, words and terms (spans of kind "term" outside base spans). rows: row (what to carry), t (the text).

    The patterns are tried once: their spans are written to the shared folder, with a key
    for each row and the text of rows that hold personal data.
    """
    found = with_base(rows).withColumn("key", F.monotonically_increasing_id())
    written = stash(found.select("key", "row", F.when(F.col("mask") > 0, F.col("t")).alias("t"), "b", "base"))
    private = written.filter(F.col("t").isNotNull())
    told = disclosing(rows.select("t"), private.select("t", "base"), alpha, support, level, prefix)
    words = disclosed_terms(private.select("key", "t", "base"), told, prefix)
    no_words, no_spans = F.array().cast("array<struct<w:string,put:string>>"), F.array().cast(SPAN)
    clean = written.filter(F.col("t").isNull()).withColumns({"words": no_words, "terms": no_spans})
    hidden = private.join(words, "key", "left").withColumn("words", F.coalesce("words", no_words))
    spans = _let(F.when(F.size("words") > 0, _any_of(F.col("words"))), lambda p: spans_of("term", F.col("t"), p))
    apart = F.filter(spans, lambda s: ~F.exists("base", lambda b: (s["start"] < b["end"]) & (b["start"] < s["end"])))
    return clean.unionByName(hidden.withColumn("terms", apart))


def _between(chunks: Column, start: Column, end: Column) -> Column:
    """The text from start to end, by code points, out of chunks of equal size."""
    first, final = F.floor(start / _CHUNK).cast("int"), F.floor(end / _CHUNK).cast("int")
    piece = lambda i: F.coalesce(F.get(chunks, i), F.lit(""))
    whole = F.array_join(F.slice(chunks, first + 2, F.greatest(final - first - 1, F.lit(0))), "")
    across = F.concat(F.substring(piece(first), start % _CHUNK + 1, F.lit(_CHUNK)), whole, F.substring(piece(final), F.lit(1), end % _CHUNK))
    return F.when(first == final, F.substring(piece(first), start % _CHUNK + 1, end - start)).otherwise(across)


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def find_spans(docs: DataFrame, row_id: str = "doc_id", text: str = "text", **measure: float) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term."""
    rows = protected(docs.select(F.col(row_id).alias("row"), text_or_empty(text).alias("t")), **measure)
    counts = [F.size(f"b.{k}").cast("long").alias(f"n_{k}") for k in KINDS]
    base = _listed(F.col("base"))
    return rows.select(F.col("row").alias("doc_id"), *counts, F.sha2(base.cast("binary"), 256).alias("base_sha256"), _listed(F.concat("base", "terms")).alias("spans"), F.size("terms").cast("long").alias("n_term"))


def sanitise(docs: DataFrame, text: str = "text", **measure: float) -> DataFrame:
    """The input columns, personal data replaced by its kind in brackets and disclosing terms by their heads."""
    carried = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    rows = protected(docs.select(carried.alias("row"), text_or_empty(text).alias("t")), **measure)
    # base spans of different kinds may overlap: those that do become one, of the first one's kind
    ordered = F.array_sort(F.transform("base", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    last = lambda acc: F.get(acc, F.size(acc) - 1)
    joined = lambda acc, s: F.concat(F.slice(acc, F.lit(1), F.size(acc) - 1), F.array(F.struct(last(acc)["start"].alias("start"), F.greatest(last(acc)["end"], s["end"]).alias("end"), last(acc)["kind"].alias("kind"))))
    merged = F.aggregate(ordered, F.array().cast("array<struct<start:int,end:int,kind:string>>"), lambda acc, s: F.when(F.coalesce(s["start"] < last(acc)["end"], F.lit(False)), joined(acc, s)).otherwise(F.concat(acc, F.array(s))))
    spans = F.array_sort(F.concat(merged, F.transform("terms", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind")))))

    def rebuilt(chunks: Column, spans: Column, heads: Column) -> Column:
        def put(s: Column) -> Column:
            general = heads[F.lower(_between(chunks, s["start"], s["end"]))]
            return F.when(s["kind"] == "term", F.coalesce(general, F.lit(""))).otherwise(F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))

        before = lambda i: F.coalesce(F.get(spans, i - 1)["end"], F.lit(0))
        pieces = F.transform(spans, lambda s, i: F.concat(_between(chunks, before(i), s["start"]), put(s)))
        return F.concat(F.array_join(pieces, ""), _between(chunks, before(F.size(spans)), F.size(chunks) * _CHUNK))

    # chunks of code points, so that no place of a long text is counted from its start
    chunks = F.regexp_extract_all(F.col("t"), F.lit(f"(?s).{{1,{_CHUNK}}}"), F.lit(0))
    done = _let(chunks, lambda c: _let(spans, lambda s: _let(F.map_from_entries("words"), lambda w: rebuilt(c, s, w))))
    changed = F.when(F.size("base") > 0, done).otherwise(F.col(f"row.`{text}`"))
    return rows.select(*(changed.alias(c) if c == text else F.col(f"row.`{c}`").alias(c) for c in docs.columns))
