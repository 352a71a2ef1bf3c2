"""The space of atomic hash functions, as Catalyst expressions and as DuckDB text.

A hash value is a string and never null: a value v becomes 'v' followed by v, a null
becomes 'n', so that null is an ordinary value that keeps its records together.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model import Attribute, BlockingSpec, HashFn, Interval

STOP_WORDS = ("the", "a", "an", "of", "and", "or", "in", "on", "to", "for", "der", "die", "das", "und", "le", "la", "les", "de", "el", "los", "y")

# constructors -----------------------------------------------------------------


def identity(a: str) -> HashFn:
    return HashFn("identity", a)


def prefix(a: str, k: int) -> HashFn:
    return HashFn("prefix", a, (k,))


def suffix(a: str, k: int) -> HashFn:
    return HashFn("suffix", a, (k,))


def top_chars(a: str, k: int) -> HashFn:
    """The k most frequent characters (ties: the smaller), in alphabetical order."""
    return HashFn("top_chars", a, (k,))


def longest_token(a: str) -> HashFn:
    """The longest white-space separated token (ties: the smaller)."""
    return HashFn("longest_token", a)


def bucket_int(a: str, k: int) -> HashFn:
    """Rounded down to a multiple of k, also below zero."""
    return HashFn("bucket_int", a, (k,))


def first_token(a: str) -> HashFn:
    return HashFn("first_token", a)


def last_token(a: str) -> HashFn:
    return HashFn("last_token", a)


def token(a: str, i: int) -> HashFn:
    """The i-th token, from 1; null where there are fewer."""
    return HashFn("token", a, (i,))


def digit_prefix(a: str, n: int) -> HashFn:
    """The first n digits, whatever stands between them."""
    return HashFn("digit_prefix", a, (n,))


def no_stopwords(a: str, words: tuple[str, ...] = STOP_WORDS) -> HashFn:
    return HashFn("no_stopwords", a, (tuple(words),))


def normalised(a: str) -> HashFn:
    """Upper case, no accents of Western languages, single spaces."""
    return HashFn("normalised", a)


def soundex(a: str) -> HashFn:
    return HashFn("soundex", a)


def date_bucket(a: str, unit: str) -> HashFn:
    return HashFn("date_bucket", a, (unit,))


def minhash(a: str, band: int, rows: int = 2, k: int = 5) -> HashFn:
    """`rows` least seeded hashes of the k-word shingles of a text."""
    return HashFn("minhash", a, (band, rows, k))


def sign_bits(a: str, planes: int, seed: int = 0) -> HashFn:
    """Sides of `planes` random hyperplanes on which a vector lies."""
    return HashFn("sign_bits", a, (planes, seed))


def interval_hash(a: str, partition: list[Interval], order: str | None = None) -> HashFn:
    """Number of the interval of an ordered attribute that holds the value; `order` is a family without parameters by whose value texts are ordered."""
    return HashFn("interval", a, tuple(partition)) if order is None else HashFn("interval_by", a, (order, *partition))


def order_key(a: Attribute, order: str | None = None) -> Column:
    """What an attribute is ordered by: itself, or the value of a family without parameters."""
    return F.expr(a.expr) if order is None else _raw(HashFn(order, a.name), a)


# expressions ------------------------------------------------------------------

_ACCENTS = ("ÀÁÂÃÄÅÇÈÉÊËÌÍÎÏÑÒÓÔÕÖÙÚÛÜÝ", "AAAAAACEEEEIIIINOOOOOUUUUY")


def _tokens(c: Column) -> Column:
    return F.filter(F.split(c, r"\s+"), lambda t: t != "")


def _by_count(s: Column) -> Column:
    """The characters of a text as structs (n, c), the most frequent first: sorted characters stand in runs, which one search cuts."""
    runs = F.regexp_extract_all(F.array_join(F.sort_array(F.split(s, "")), ""), F.lit(r"(?s)(.)\1*+"), F.lit(0))
    return F.array_sort(F.transform(runs, lambda r: F.struct((-F.length(r)).alias("n"), F.left(r, F.lit(1)).alias("c"))))


def _first_token(c: Column) -> Column:
    """The search ends with the first token, however long the text is."""
    return F.nullif(F.regexp_extract(c, r"(\S+)", 1), F.lit(""))


def _raw(h: HashFn, a: Attribute) -> Column:
    c = F.expr(a.expr)
    s = c.cast("string")
    p = h.params
    match h.family:
        case "identity":
            return s
        case "prefix":
            return F.substring(s, 1, p[0])
        case "suffix":
            return F.right(s, F.lit(p[0]))
        case "top_chars":
            return F.array_join(F.array_sort(F.transform(F.slice(_by_count(s), 1, p[0]), lambda x: x["c"])), "")
        case "longest_token":
            best = F.array_min(F.transform(_tokens(s), lambda t: F.struct((-F.length(t)).alias("n"), t.alias("t"))))
            return best["t"]
        case "bucket_int":
            return (c - F.pmod(c, F.lit(p[0]))).cast("bigint").cast("string")
        case "first_token":
            return _first_token(s)
        case "last_token":
            return F.reverse(_first_token(F.reverse(s)))
        case "token":
            return F.get(_tokens(s), F.lit(p[0] - 1))
        case "digit_prefix":
            return F.substring(F.regexp_replace(s, "[^0-9]", ""), 1, p[0])
        case "no_stopwords":
            stop = F.array(*[F.lit(w) for w in p[0]])
            return F.array_join(F.filter(_tokens(F.lower(s)), lambda t: ~F.array_contains(stop, t)), " ")
        case "normalised":
            return F.trim(F.regexp_replace(F.translate(F.upper(s), *_ACCENTS), r"\s+", " "))
        case "soundex":
            return F.soundex(s)
        case "date_bucket":
            return F.date_format(F.date_trunc(p[0], c), "yyyy-MM-dd")
        case "minhash":
            band, rows, k = p
            words = _tokens(F.lower(s))
            runs = F.when(F.size(words) <= k, F.array(F.array_join(words, " "))).otherwise(F.transform(F.sequence(F.lit(1), F.size(words) - k + 1), lambda i: F.array_join(F.slice(words, i, k), " ")))

            def least(row: int) -> Column:
                # a function of one argument: a second one would be the place in the array
                return F.array_min(F.transform(runs, lambda r: F.xxhash64(r, F.lit(band * 1000 + row)))).cast("string")

            return F.concat_ws("-", *[least(i) for i in range(rows)])
        case "sign_bits":
            return _signs(c, p[0], p[1])
        case "interval":
            return interval_number(c, p)
        case "interval_by":
            return interval_number(order_key(a, p[0]), p[1:])
    raise ValueError(f"unknown hash family {h.family}")


def _signs(c: Column, planes: int, seed: int) -> Column:
    """Side of each plane; coefficients of plane j at place i are the signs of a seeded hash of (j, i)."""
    v = c.cast("array<double>")

    def dot(j: int) -> Column:
        signed = F.transform(v, lambda x, i: F.when(F.xxhash64(i, F.lit(seed * 1000 + j)) >= 0, x).otherwise(-x))
        return F.aggregate(signed, F.lit(0.0), lambda acc, x: acc + F.coalesce(x, F.lit(0.0)))

    return F.when(v.isNotNull(), F.concat(*[F.when(dot(j) >= 0, "1").otherwise("0") for j in range(planes)]))


def interval_number(c: Column, cuts: tuple[Interval, ...]) -> Column:
    """Number of the interval that holds c, by nested tests of upper ends that halve what is left; the last interval has none."""

    def search(lo: int, hi: int) -> Column:
        if lo == hi:
            return F.lit(str(lo))
        m = (lo + hi) // 2
        end = F.lit(cuts[m].hi)
        return F.when((c <= end) if cuts[m].hi_incl else (c < end), search(lo, m)).otherwise(search(m + 1, hi))

    return F.when(c.isNotNull(), search(0, len(cuts) - 1))


def shared(library: list[HashFn], spec: BlockingSpec, least: int = 2) -> dict[str, Column]:
    """Helper columns that at least `least` functions of a library need, by name: the characters by count of an attribute."""
    several = [a for a in spec.attributes if sum(h.family == "top_chars" and h.attribute == a.name for h in library) >= least]
    return {f"__chars_{a.name}": F.slice(_by_count(F.expr(a.expr).cast("string")), 1, max(h.params[0] for h in library if h.family == "top_chars" and h.attribute == a.name)) for a in several}


def columns(df: DataFrame, library: list[HashFn], spec: BlockingSpec, *keep: Column) -> DataFrame:
    """`keep` and the tagged values h0, h1, ... of a library; what functions share is computed once a record."""
    helpers = shared(library, spec)
    return df.withColumns(helpers).select(*keep, *[column(h, spec, helpers).alias(f"h{i}") for i, h in enumerate(library)])


def column(h: HashFn, spec: BlockingSpec, helpers=()) -> Column:
    """The tagged value of a hash function as an expression; a string that is never null. helpers: names of `shared` columns that are there."""
    name = f"__chars_{h.attribute}"
    if h.family == "top_chars" and name in helpers:
        value = F.array_join(F.array_sort(F.transform(F.slice(name, 1, h.params[0]), lambda x: x["c"])), "")
        return F.coalesce(F.concat(F.lit("v"), value), F.lit("n"))
    return F.coalesce(F.concat(F.lit("v"), _raw(h, spec.attribute(h.attribute))), F.lit("n"))


def _quote(x) -> str:
    return "'" + str(x).replace("'", "''") + "'"


def _duck(h: HashFn, a: Attribute) -> str:
    c, p = f"({a.sql})", h.params
    s = f"CAST({c} AS VARCHAR)"
    toks = f"list_filter(string_split_regex({s}, '\\s+'), lambda t: t <> '')"
    match h.family:
        case "identity":
            return s
        case "prefix":
            return f"left({s}, {p[0]})"
        case "suffix":
            return f"right({s}, {p[0]})"
        case "top_chars":
            chars = f"string_split({s}, '')"
            count = f"list_transform(list_distinct({chars}), lambda x: {{'n': length(replace({s}, x, '')) - length({s}), 'c': x}})"
            return f"CASE WHEN {s} = '' THEN '' ELSE array_to_string(list_sort(list_transform(list_slice(list_sort({count}), 1, {p[0]}), lambda y: y.c)), '') END"
        case "longest_token":
            return f"list_sort(list_transform({toks}, lambda t: {{'n': -length(t), 't': t}}))[1].t"
        case "bucket_int":
            return f"CAST(CAST({c} - (({c} % {p[0]}) + {p[0]}) % {p[0]} AS BIGINT) AS VARCHAR)"
        case "first_token":
            return f"{toks}[1]"
        case "last_token":
            return f"{toks}[-1]"
        case "token":
            return f"{toks}[{p[0]}]"
        case "digit_prefix":
            return f"left(regexp_replace({s}, '[^0-9]', '', 'g'), {p[0]})"
        case "no_stopwords":
            words = ", ".join(_quote(w) for w in p[0])
            return f"array_to_string(list_filter(list_filter(string_split_regex(lower({s}), '\\s+'), lambda t: t <> ''), lambda t: NOT list_contains([{words}], t)), ' ')"
        case "normalised":
            return f"trim(regexp_replace(translate(upper({s}), {_quote(_ACCENTS[0])}, {_quote(_ACCENTS[1])}), '\\s+', ' ', 'g'))"
        case "date_bucket":
            return f"strftime(date_trunc({_quote(p[0])}, {c}), '%Y-%m-%d')"
        case "interval" | "interval_by":
            def lit(v):
                return str(v) if isinstance(v, (int, float)) else f"{_quote(v)}"
            if h.family == "interval_by":
                c, p = f"({_duck(HashFn(p[0], a.name), a)})", p[1:]
            tests = " ".join(f"WHEN {c} {'<=' if x.hi_incl else '<'} {lit(x.hi)} THEN '{i}'" for i, x in enumerate(p) if x.hi is not None)
            last = len(p) - 1
            return f"CASE WHEN {c} IS NULL THEN NULL {tests} ELSE '{last}' END"
    raise ValueError(f"{h.family} has no DuckDB twin")


def duck_sql(h: HashFn, spec: BlockingSpec) -> str:
    """DuckDB text of the tagged value."""
    return f"coalesce('v' || {_duck(h, spec.attribute(h.attribute))}, 'n')"


def default_library(spec: BlockingSpec, k: tuple[int, ...] = (1, 3, 5), without: tuple[str, ...] = ()) -> list[HashFn]:
    """All functions that the attributes' kinds suggest, by name; `without` leaves families out."""
    out: list[HashFn] = []
    for a in spec.attributes:
        n = a.name
        out.append(identity(n))
        if a.kind in ("text", "token_text", "code"):
            out += [f(n, i) for f in (prefix, suffix, top_chars) for i in k]
        if a.kind == "token_text":
            out += [longest_token(n), first_token(n), last_token(n)]
        if a.kind == "code":
            out.append(digit_prefix(n, 3))
        if a.kind in ("int", "float"):
            out += [bucket_int(n, i) for i in (2, 5, 10, 100, 1000)]
        if a.kind in ("date", "timestamp"):
            out += [date_bucket(n, u) for u in ("week", "month", "year")]
    return sorted((h for h in out if h.family not in without), key=lambda h: h.name)
