"""Secrets in texts: strong patterns on their own, weak ones only next to their complement.

Three base kinds are reported wherever they stand: ``assign`` (a secret name with a value), ``access`` (an access
identifier) and ``hex`` (a long hexadecimal run). Three weak kinds mean nothing alone: ``account`` (a user or client name with
a value), ``random`` (forty mixed characters) and ``endpoint`` (an address of a service). A credential has
several parts: an identifier or endpoint, and a secret. So spans are joined by intervals: a weak span is reported if, within
SCOPE code points, a part of the other role lies (identifiers: access, account, endpoint; secrets: assign,
hex, random). A weak span that a base span overlaps is left out.

All of it is column expressions in one narrow pass: no shuffle, no Python. Regular-expression functions give matches and the gaps
between them; positions are sums of lengths, added up in blocks. The interval joins sweep parts and questions in
one order of places and look at the furthest end so far; running maxima are taken by blocks too. So work is that of sorting the
matches, plus (matches / 64) squared in cheap steps. ``redact`` cuts the text into blocks once and puts the pieces together from these.

Cases: null text is empty text and has no spans; positions are in code points, ends exclusive; equal spans of two kinds are
both reported; repeated rows each get a row; an empty table gives an empty table; other columns are
ignored by ``scan_documents`` and passed through by ``redact``.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Code points between parts of one credential.
SCOPE = 200
#: Numbers of a block of sums and maxima; code points of a block of text.
_SUM_BLOCK, _TEXT_BLOCK = 64, 1024

_NOWHERE = -(1 << 30)
_VALUE = "[A-Za-z0-9+/_.=-]"
#: kind -> pattern and, where group 1 has a least length, that length. Base kinds first; the order breaks ties of starts.
PATTERNS: dict[str, tuple[str, int]] = {
    "assign": (rf"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?({_VALUE}+)", 6),
    "access": (r"AKIA[A-Z0-9]{16,}", 0),
    "hex": (r"[0-9a-f]{24,}", 0),
    "account": (r"(?i:user_?name|user|login|account|client_?id|access_?key_?id)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9@._-]+)", 3),
    "random": (r"(?<![A-Za-z0-9+/])(?=[A-Za-z+/]{0,39}[0-9])(?=[^a-z]{0,39}[a-z])(?=[^A-Z]{0,39}[A-Z])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/])", 0),
    "endpoint": (r"(?i:https?|postgres(?:ql)?|mysql|mongodb|redis|amqp|ftp|ssh)://[^\x00-\x20\"'<>]+", 0),
}
BASE = ("assign", "access", "hex")
_SECRET, _NAMED = ("assign", "hex", "random"), ("access", "account", "endpoint")
_ORDER = {kind: i for i, kind in enumerate(PATTERNS)}


def _col(kind: str, what: str) -> str:
    return f"__{what}_{kind}"


def _total(numbers: Column) -> Column:
    return F.aggregate(numbers, F.lit(0), lambda a, x: a + x)


def _per_index(n: Column, make: Callable[[Column], Column], empty: str) -> Column:
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), make)).otherwise(F.from_json(F.lit("[]"), empty))


def _let(value: Column, make: Callable[[Column], Column]) -> Column:
    """``make`` of a value that is worked out once, even where the optimiser puts its expression in the place of its column."""
    return F.element_at(F.transform(F.array(value), make), 1)


def _staged(df: DataFrame, columns: dict[str, Column]) -> DataFrame:
    return df.select("*", *(c.alias(name) for name, c in columns.items()))


_SHAPE = "array<struct<start:int,rank:int,kind:string,end:int>>"


def _block_sums(kind: str) -> Column:
    d = F.col(_col(kind, "d"))
    n = F.ceil(F.size(_col(kind, "m")) / F.lit(_SUM_BLOCK)).cast("int")
    return _per_index(n, lambda b: _total(F.slice(d, b * _SUM_BLOCK + 1, _SUM_BLOCK)), "array<int>")


def _block_starts(kind: str) -> Column:
    sums = F.col(_col(kind, "b"))
    return _per_index(F.size(sums), lambda b: _total(F.slice(sums, F.lit(1), b)), "array<int>")


def _spans_of(kind: str) -> Column:
    d, base, m, lengths = (F.col(_col(kind, x)) for x in ("d", "base", "m", "l"))
    pattern, least = PATTERNS[kind]

    def span(i: Column, before: Column) -> Column:
        block = F.floor(i / F.lit(_SUM_BLOCK)).cast("int")
        start = F.element_at(before, block + 1) + _total(F.slice(d, block * _SUM_BLOCK + 1, i - block * _SUM_BLOCK + 1))
        return F.struct(start.alias("start"), F.lit(_ORDER[kind]).alias("rank"), F.lit(kind).alias("kind"), (start + F.element_at(lengths, i + 1)).alias("end"))

    got = _let(base, lambda before: _per_index(F.size(m), lambda i: span(i, before), _SHAPE))
    if least:
        paired = F.zip_with(got, m, lambda s, x: F.struct(s.alias("s"), F.length(F.regexp_extract(x, pattern, 1)).alias("n")))
        got = F.transform(F.filter(paired, lambda x: x["n"] >= least), lambda x: x["s"])
    return got


def with_spans(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The input with a column ``__spans``: array<struct<start, rank, kind, end>>, base and linked weak spans in order. Each stage
    is a projection of its own, so that no regular expression runs twice on a text."""
    kinds = list(PATTERNS)
    df = _staged(docs, {"__text": F.coalesce(F.col(text_col), F.lit(""))})
    df = _staged(df, {_col(k, "m"): F.regexp_extract_all("__text", F.lit(PATTERNS[k][0]), F.lit(0)) for k in kinds})

    gaps = {}
    for k in kinds:
        m = F.col(_col(k, "m"))
        between = F.split(F.col("__text"), PATTERNS[k][0], -1)
        gaps[_col(k, "g")] = F.when(F.size(m) > 0, F.transform(between, lambda x: F.length(x)))
        gaps[_col(k, "l")] = F.transform(m, lambda x: F.length(x))
    df = _staged(df, gaps)

    # Step i: from the start of match i - 1 to the start of match i.
    df = _staged(df, {_col(k, "d"): F.zip_with(F.slice(F.col(_col(k, "g")), 1, F.size(_col(k, "m"))), F.concat(F.array(F.lit(0)), F.col(_col(k, "l"))), lambda a, b: F.coalesce(a, F.lit(0)) + b) for k in kinds})
    df = _staged(df, {_col(k, "b"): _block_sums(k) for k in kinds})
    df = _staged(df, {_col(k, "base"): _block_starts(k) for k in kinds})
    df = _staged(df, {_col(k, "s"): _spans_of(k) for k in kinds})
    every = lambda names: F.concat(*(F.col(_col(k, "s")) for k in names))
    df = _staged(df, {"__base": F.sort_array(every(BASE)), "__secret": every(_SECRET), "__named": every(_NAMED)})
    weak = F.filter(F.concat("__secret", "__named"), lambda s: s["rank"] >= len(BASE))
    df = _staged(df, {"__weak": F.when((F.size("__secret") > 0) & (F.size("__named") > 0), weak).otherwise(F.from_json(F.lit("[]"), _SHAPE))})

    # Parts at their starts and weak spans where their reach ends, in one order: the furthest end so far of the other role tells whether a part meets the span.
    role = lambda s: s["kind"].isin(*_SECRET)
    parts = F.transform(F.concat("__secret", "__named"), lambda s: _event(s["start"], 0, s, F.when(role(s), s["end"]).otherwise(_NOWHERE), F.when(role(s), F.lit(_NOWHERE)).otherwise(s["end"])))
    df = _staged(df, {"__meet": _swept("__weak", parts, lambda s: s["end"] + SCOPE)})
    df = _running_max(_running_max(df, "__meet", "first"), "__meet", "second")
    df = _staged(df, {"__met": _reached("__meet", "__meet_first", "__meet_second", lambda e, first, second: F.when(role(e["span"]), second).otherwise(first) >= e["span"]["start"] - SCOPE)})

    bases = F.transform("__base", lambda s: _event(s["start"], 0, s, s["end"], F.lit(_NOWHERE)))
    df = _staged(df, {"__over": _swept("__met", bases, lambda s: s["end"] - 1)})
    df = _running_max(df, "__over", "first")
    df = _staged(df, {"__free": _reached("__over", "__over_first", "__over_first", lambda e, first, _: first <= e["span"]["start"])})
    return df.select(*docs.columns, "__text", "__base", F.sort_array(F.concat("__base", "__free")).alias("__spans"))


def _event(at: Column, turn: int, span: Column, first: Column, second: Column) -> Column:
    return F.struct(at.alias("at"), F.lit(turn).alias("turn"), span.alias("span"), first.alias("first"), second.alias("second"))


def _swept(spans: str, parts: Column, until: Callable[[Column], Column]) -> Column:
    """Parts, and spans as questions at ``until``, in order of place, parts first; empty where there is no span."""
    asked = F.transform(spans, lambda s: _event(until(s), 1, s, F.lit(_NOWHERE), F.lit(_NOWHERE)))
    return F.when(F.size(spans) > 0, F.sort_array(F.concat(parts, asked))).otherwise(F.slice(asked, 1, 0))


def _running_max(df: DataFrame, events: str, what: str) -> DataFrame:
    """Adds the running maximum of a field of ``events``, by blocks, as column events_what."""
    name = f"{events}_{what}"
    df = _staged(df, {f"{name}_v": F.transform(events, lambda e: e[what])})
    v, blocks, base = F.col(f"{name}_v"), F.col(f"{name}_b"), F.col(f"{name}_a")
    n = F.ceil(F.size(v) / F.lit(_SUM_BLOCK)).cast("int")
    df = _staged(df, {f"{name}_b": _per_index(n, lambda b: F.array_max(F.slice(v, b * _SUM_BLOCK + 1, _SUM_BLOCK)), "array<int>")})
    df = _staged(df, {f"{name}_a": _per_index(F.size(blocks), lambda b: F.array_max(F.slice(blocks, F.lit(1), b)), "array<int>")})

    def upto(i: Column, before: Column) -> Column:
        block = F.floor(i / F.lit(_SUM_BLOCK)).cast("int")
        return F.greatest(F.element_at(before, block + 1), F.array_max(F.slice(v, block * _SUM_BLOCK + 1, i - block * _SUM_BLOCK + 1)))

    return _staged(df, {name: _let(base, lambda before: _per_index(F.size(v), lambda i: upto(i, before), "array<int>"))})


def _reached(events: str, first: str, second: str, holds: Callable[[Column, Column, Column], Column]) -> Column:
    """The spans of the questions for which ``holds`` is true of the event and two running maxima."""
    pairs = F.zip_with(F.zip_with(first, second, lambda a, b: F.struct(a.alias("a"), b.alias("b"))), events, lambda m, e: F.struct(m.alias("m"), e.alias("e")))
    return F.transform(F.filter(pairs, lambda x: (x["e"]["turn"] == 1) & holds(x["e"], x["m"]["a"], x["m"]["b"])), lambda x: x["e"]["span"])


def _joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def scan_documents(docs: DataFrame) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex, base_sha256, spans) of every document."""
    df = with_spans(docs.select("doc_id", "text"))
    count = lambda k: F.size(F.filter("__base", lambda s: s["kind"] == k)).cast("bigint").alias(f"n_{k}")
    return df.select("doc_id", *(count(k) for k in BASE), F.sha2(_joined(F.col("__base")), 256).alias("base_sha256"), _joined(F.col("__spans")).alias("spans"))


def redact(docs: DataFrame, mask: str = "[SECRET]") -> DataFrame:
    """The rows with each union of overlapping spans of ``text`` replaced by the mask, n_chars (if there) recounted where
    text changed; null text stays null. Other columns are as they were."""
    df = with_spans(docs)
    n = F.size("__spans")
    df = _staged(df, {"__ends": F.transform("__spans", lambda s: F.struct(s["end"].alias("first")))})
    df = _running_max(df, "__ends", "first")
    upto = lambda i: F.element_at("__ends_first", i + 1)
    df = _staged(df, {"__heads": F.filter(_per_index(n, lambda i: i, "array<int>"), lambda i: (i == 0) | (F.element_at("__spans", i + 1)["start"] >= upto(F.greatest(i - 1, F.lit(0)))))})
    df = _staged(df, {"__blocks": F.when(n > 0, F.regexp_extract_all("__text", F.lit(f"(?s).{{1,{_TEXT_BLOCK}}}"), F.lit(0)))})

    def piece(a: Column, b: Column) -> Column:
        first, last = (F.floor(x / F.lit(_TEXT_BLOCK)).cast("int") for x in (a, b - 1))
        block = lambda k: F.element_at("__blocks", k + 1)
        within = block(first).substr(a % _TEXT_BLOCK + 1, b - a)
        across = F.concat(block(first).substr(a % _TEXT_BLOCK + 1, F.lit(_TEXT_BLOCK)), F.array_join(F.slice("__blocks", first + 2, F.greatest(last - first - 1, F.lit(0))), ""), block(last).substr(F.lit(1), (b - 1) % _TEXT_BLOCK + 1))
        return F.when(a >= b, F.lit("")).when(first == last, within).otherwise(across)

    heads = F.size("__heads")
    head = lambda j: F.element_at("__heads", j + 1)
    from_ = lambda j: F.when(j == 0, F.lit(0)).when(j < heads, upto(head(F.least(j, heads - 1)) - 1)).otherwise(upto(n - 1))
    to = lambda j: F.when(j < heads, F.element_at("__spans", head(F.least(j, heads - 1)) + 1)["start"]).otherwise(F.length("__text"))
    pieces = F.transform(F.sequence(F.lit(0), heads), lambda j: piece(from_(j), to(j)))
    df = df.withColumn("__new", F.when(n > 0, F.array_join(pieces, mask)).otherwise(F.col("text")))
    out = []
    for c in docs.columns:
        if c == "text":
            out.append(F.col("__new").alias("text"))
        elif c == "n_chars":
            out.append(F.when(F.size("__spans") > 0, F.length("__new").cast(docs.schema[c].dataType)).otherwise(F.col(c)).alias(c))
        else:
            out.append(F.col(c))
    return df.select(*out)
