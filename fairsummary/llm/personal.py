"""Personal data by fixed patterns and by bootstrapped contexts, on built-in functions only.

Fixed patterns find e-mail addresses, network addresses, card and phone
numbers.  Those seeds induce lexical patterns (the words in front of each);
patterns, seeds and identifier-like tokens form a graph that is scored in
rounds until nothing changes: a pattern is trusted when most of the distinct
tokens behind it are known, and tokens behind trusted patterns become known in
turn.  What trusted patterns find beside the seeds is added.  Everything is
JVM-side.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, sized

KINDS = ("email", "ip", "card", "phone")

# The base patterns, in forms that cannot backtrack over long runs.  Lookbehinds
# only skip starts from which the plain pattern finds the same match or none.
_LOCAL = "A-Za-z0-9._%+-"
PATTERNS = {
    "email": rf"(?:\G|(?<![{_LOCAL}]))[{_LOCAL}]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?<![0-9])(?<![0-9][\x20-])[0-9](?:[\x20-]?[0-9]){15,18}(?![\x20-]?[0-9])",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
_OCTET = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[0-9]{1,2})"
_UNIT = r"""[^\s0-9@:=;|<>"'\[\]{}]*+[0-9@][^\s:=;|<>"'\[\]{}]*+"""
#: An identifier-like token: a run with a digit or an @, and up to five more such runs after single spaces.
TOKEN = rf"""(?<![^\s:=;|<>("'\[{{#])(?=[\p{{L}}0-9+@]){_UNIT}(?:\x20{_UNIT}){{0,5}}"""
#: One or two words in front, with opening brackets and quotes left out; the last may end in a colon or the like that touches.
CONTEXT = r"""((?:\S+\s+)?\S+?)(?:\s+|(?<=[:=;|]))[<("'\[{#]*$"""
SPAN = "struct<kind:int,s:int,e:int,hit:string>"


def _cheap(kind: str, text: Column) -> Column:
    """A quick necessary condition, so that most texts never meet the pattern."""
    if kind == "email":
        return text.contains("@")
    if kind == "phone":
        return text.contains("+")
    return text.rlike(r"[0-9]\.[0-9]" if kind == "ip" else r"[0-9][\x20-]?[0-9][\x20-]?[0-9][\x20-]?[0-9]")


def _valid(kind: str, hit: Column) -> Column:
    digits = F.regexp_replace(hit, "[^0-9]", "")
    if kind == "ip":
        return hit.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$")
    if kind == "card":
        return F.length(digits).between(16, 19) & F.call_function("luhn_check", digits)
    if kind == "phone":
        return F.length(digits).between(8, 15)
    return F.lit(True)


def _accepts(kind: str):
    return lambda x: _valid(kind, x["hit"])


def _is_kind(number: int):
    return lambda x: x["kind"] == number


def located(text: Column, pattern: str, kind: int) -> Column:
    """Matches with their code-point spans: lengths of the gaps between matches and of the matches, added up."""
    gaps, hits = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(f"array<{SPAN}>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        s = (acc["at"] + F.length(x["gap"])).cast("int")
        e = (s + F.length(x["hit"])).cast("int")
        return F.struct(e.alias("at"), F.concat(acc["out"], F.array(F.struct(F.lit(kind).alias("kind"), s.alias("s"), e.alias("e"), x["hit"].alias("hit")))).alias("out"))

    pairs = F.zip_with(F.slice(gaps, 1, F.size(hits)), hits, lambda g, h: F.struct(g.alias("gap"), h.alias("hit")))
    return F.aggregate(pairs, start, step, lambda acc: acc["out"])


def base_spans(text: Column) -> Column:
    """Valid base spans of a text, by kind in the order of KINDS, then by start."""
    none = F.array().cast(f"array<{SPAN}>")
    parts = [F.when(_cheap(k, text), F.filter(located(text, PATTERNS[k], i), _accepts(k))).otherwise(none) for i, k in enumerate(KINDS)]
    return F.concat(*parts)


def _shape(column: Column) -> Column:
    """Lower case, digits as 0."""
    return F.regexp_replace(F.lower(column), "[0-9]", "0")


def _blanked(text: Column, base: Column) -> Column:
    """The text with spaces for its base spans."""
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        gap = F.substring(text, acc["at"] + 1, F.greatest(x["s"] - acc["at"], F.lit(0)))
        fill = F.repeat(F.lit(" "), F.greatest(x["e"] - F.greatest(x["s"], acc["at"]), F.lit(0)))
        return F.struct(F.greatest(acc["at"], x["e"]).cast("int").alias("at"), F.concat(acc["out"], gap, fill).alias("out"))

    ends = F.array_sort(F.transform(base, lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"))))
    return F.when(F.size(base) == 0, text).otherwise(F.aggregate(ends, start, step, lambda acc: F.concat(acc["out"], F.substring(text, acc["at"] + 1, F.length(text)))))


def candidates(docs: DataFrame) -> DataFrame:
    """Base spans and, beside them, identifier-like tokens of (doc_id, text_key, text, base): (.., s, e, token, pattern, known), one row each.

    The pattern is what stands in front of the span's or token's own start; base spans are known.
    """
    def as_span(known: bool):
        return lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["hit"].alias("hit"), F.lit(known).alias("known"))

    spans = F.concat(F.transform("base", as_span(True)), F.transform(located(F.col("blank"), TOKEN, len(KINDS)), as_span(False)))
    rows = docs.withColumn("blank", _blanked(F.col("text"), F.col("base"))).select("doc_id", "text_key", "text", F.explode(spans).alias("x"))
    tail = F.regexp_extract("x.hit", r"[^A-Za-z0-9]*$", 0)
    e = (F.col("x.e") - F.length(tail)).cast("int")
    left = F.expr("substring(text, greatest(x.s - 79, 1), least(x.s, 80))")
    pattern = _shape(F.regexp_extract(left, CONTEXT, 1))
    return rows.select("doc_id", "text_key", F.col("x.s").alias("s"), e.alias("e"), F.lower(F.regexp_replace("x.hit", r"[^A-Za-z0-9]+$", "")).alias("token"), F.regexp_replace(pattern, r"\s+", " ").alias("pattern"), F.col("x.known").alias("known")).where("s < e")


def bootstrap(found: DataFrame, *, support: int = 3, trust: float = 0.6) -> DataFrame:
    """Trusted patterns once rounds on the pattern-token graph change nothing; known tokens only grow, so that comes.

    A pattern is trusted with at least ``support`` distinct known tokens that
    make up at least the share ``trust`` of the distinct tokens behind it; then
    the tokens behind it are known.  Counts cover all rows; edges are distinct
    before they are counted, so copies of a text add nothing.
    """
    edges = materialize(found.where("pattern <> ''").groupBy("pattern", "token").agg(F.max("known").alias("known")), "edges")
    trusted = None
    while True:
        score = edges.groupBy("pattern").agg(F.count("*").alias("n"), F.count_if("known").alias("k"))
        score = materialize(score.where((F.col("k") >= support) & (F.col("k") >= trust * F.col("n"))).select("pattern"), "patterns")
        if score.isEmpty():
            return score
        size = score.count()
        if size == trusted:
            return score
        trusted = size
        reached = edges.join(sized(score), "pattern", "left_semi").where("NOT known").select("token").distinct()
        reached = sized(materialize(reached, "reached").withColumn("now", F.lit(True)))
        edges = materialize(edges.join(reached, "token", "left").select("pattern", "token", (F.col("known") | F.coalesce("now", F.lit(False))).alias("known")), "edges")


def find(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_key, base, added): spans of every row, null texts being empty.

    ``base`` holds the valid base spans by kind and start, ``added`` those of the
    bootstrapped contexts by start; the two never overlap.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(text_col).alias("text_key"), text.alias("text"))
    seeds = rows.where(F.col("text").rlike("[0-9]") | F.col("text").contains("@")).withColumn("base", base_spans(F.col("text")))
    seeds = materialize(seeds.select("doc_id", "text_key", "base", "text"), "seeds")
    found = materialize(candidates(seeds), "candidates")
    patterns = bootstrap(found)
    fresh = found.where("NOT known").join(sized(patterns), "pattern", "left_semi").select("doc_id", "text_key", "s", "e").distinct()
    added = fresh.groupBy("doc_id", "text_key").agg(F.array_sort(F.collect_list(F.struct("s", "e"))).alias("added"))
    spans = seeds.select("doc_id", "text_key", F.transform("base", lambda x: F.struct(x["kind"].alias("kind"), x["s"].alias("s"), x["e"].alias("e"))).alias("base")).where("size(base) > 0").groupBy("doc_id", "text_key").agg(F.first("base").alias("base"))
    both = spans.join(added, ["doc_id", "text_key"], "full") if not patterns.isEmpty() else spans.withColumn("added", F.lit(None).cast("array<struct<s:int,e:int>>"))
    return materialize(both, "spans")


def _with_spans(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    spans = sized(find(docs, id_col=id_col, text_col=text_col).toDF("__id", "__key", "__base", "__added"))
    key, text = F.col(id_col).cast("long"), F.xxhash64(text_col)
    rows = docs.withColumns({"__i": key, "__k": text})
    joined = rows.join(spans, rows["__i"].eqNullSafe(spans["__id"]) & (rows["__k"] == spans["__key"]), "left").drop("__i", "__k", "__id", "__key")
    return joined.withColumns({"__base": F.coalesce("__base", F.array().cast("array<struct<kind:int,s:int,e:int>>")), "__added": F.coalesce("__added", F.array().cast("array<struct<s:int,e:int>>"))})


def redact(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Documents with every span replaced by its kind in brackets; spans that overlap become one.

    Null texts stay null.  All columns stay as they are but the text.
    """
    rows = _with_spans(docs, id_col, text_col)
    names = F.array(*[F.lit(f"[{k.upper()}]") for k in (*KINDS, "identifier")])
    spans = F.concat(F.transform("__base", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["kind"].alias("kind"))), F.transform("__added", lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), F.lit(len(KINDS)).alias("kind"))))
    start = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        gap = F.substring(F.col(text_col), acc["at"] + 1, F.greatest(x["s"] - acc["at"], F.lit(0)))
        tag = F.when(x["s"] >= acc["at"], F.element_at(names, x["kind"] + 1)).otherwise(F.lit(""))
        return F.struct(F.greatest(acc["at"], x["e"]).cast("int").alias("at"), F.concat(acc["out"], gap, tag).alias("out"))

    rest = F.aggregate(F.array_sort(spans), start, step, lambda acc: F.concat(acc["out"], F.substring(F.col(text_col), acc["at"] + 1, F.length(text_col))))
    return rows.withColumn(text_col, F.when(F.size("__base") + F.size("__added") > 0, rest).otherwise(F.col(text_col))).drop("__base", "__added").select(docs.columns)


def digest(docs: DataFrame) -> DataFrame:
    """doc_id, counts by kind, base_sha256 and spans of every document."""
    rows = _with_spans(docs.select("doc_id", "text"), "doc_id", "text")
    names = F.array(*map(F.lit, KINDS))
    base = F.transform("__base", lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["s"], x["e"]))
    added = F.transform("__added", lambda x: F.concat_ws(":", F.lit("identifier"), x["s"], x["e"]))
    counts = [F.size(F.filter("__base", _is_kind(i))).cast("long").alias(f"n_{k}") for i, k in enumerate(KINDS)]
    return rows.select("doc_id", *counts, F.sha2(F.array_join(base, ",").cast("binary"), 256).alias("base_sha256"), F.array_join(F.concat(base, added), ",").alias("spans"))


def brute_force(text: str | None) -> list[tuple[str, int, int]]:
    """The base spans by the plain patterns, in Python."""
    import re

    text = text or ""

    def luhn(d: str) -> bool:
        return sum(sum(divmod(2 * int(c), 10)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10 == 0

    out = []
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text):
        out.append(("email", *m.span()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text):
        if all(int(p) <= 255 for p in m[0].split(".")):
            out.append(("ip", *m.span()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub("[^0-9]", "", m[0])
        if 16 <= len(d) <= 19 and luhn(d):
            out.append(("card", *m.span()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 8 <= len(re.sub("[^0-9]", "", m[0])) <= 15:
            out.append(("phone", *m.span()))
    return out
