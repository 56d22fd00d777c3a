"""Personal data in texts, with DataFrame functions only.

Patterns propose spans, validators confirm them (parts of an address, Luhn for cards, digit counts for phones, the
remainder modulo 97 for bank accounts, a digit in the value of a named secret), and words just before a span raise its score. The places of the matches
come from the lengths of the pieces between them: splitting and extracting by one pattern see the same matches.

Possessive repeats and the look-behinds only spare work: they forbid starts inside a run whose first start failed
for a reason that holds for all of them, so that long runs take linear time. A match may also start right where the
last one ended.

Null and empty texts have no spans. Failing matches are dropped without another try. Kinds may overlap each other.
Repeated rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The patterns by kind, in the order of the results.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "iban": r"[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}",
    "secret": r"(?i:token|api_?key|secret|password)\x20*[=:]\x20*[\"']?[A-Za-z0-9+/_-]{16,}+",
}
BASE = ("email", "ip", "card", "phone")
# Words that make a kind likelier, and the scores without them.
CONTEXT = {
    "email": "mail|contact|write|address",
    "ip": r"\bip\b|host|server|address|login",
    "card": "card|visa|master|credit|pay",
    "phone": "phone|tel|call|mobile|fax",
    "iban": "iban|account|bank|konto|compte|cuenta",
    "secret": "auth|login|config|access",
}
SCORE = {"email": 0.9, "ip": 0.6, "card": 0.8, "phone": 0.5, "iban": 0.9, "secret": 0.8}
# A character without which a kind cannot occur: a cheap test before the pattern.
NEEDS = {"email": "@", "ip": ".", "phone": "+"}
REACH = 40

_SPAN = "array<struct<kind: string, start: int, end: int, score: double>>"


def _digits(hit: Column) -> Column:
    return F.regexp_replace(hit, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    n = F.length(digits)

    def part(i: Column) -> Column:  # i counts from the last digit
        d = F.substring(digits, n - i, F.lit(1)).cast("int")
        twice = d * 2
        return F.when(i % 2 == 1, F.when(twice > 9, twice - 9).otherwise(twice)).otherwise(d)

    return F.aggregate(F.transform(F.sequence(F.lit(0), n - 1), part), F.lit(0), lambda a, x: a + x) % 10 == 0


def _mod97(hit: Column) -> Column:
    turned = F.concat(F.substring(hit, F.lit(5), F.length(hit)), F.substring(hit, 1, 4))
    symbols = F.filter(F.split(turned, ""), lambda c: c != "")

    def step(a: Column, c: Column) -> Column:
        return F.when(c.rlike("[0-9]"), (a * 10 + F.ascii(c) - 48) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97)

    return F.aggregate(symbols, F.lit(0), step) == 1


def _valid(kind: str, hit: Column) -> Column:
    if kind == "ip":
        bare = lambda p: F.regexp_replace(p, "^0+(?=.)", "")  # noqa: E731  without leading zeros
        return F.forall(F.split(hit, r"\."), lambda p: F.when(F.length(bare(p)) <= 3, bare(p).cast("int") <= 255).otherwise(F.lit(False)))
    if kind == "card":
        d = _digits(hit)
        return F.when(F.length(d).between(16, 19), _luhn(d)).otherwise(F.lit(False))
    if kind == "phone":
        return F.length(_digits(hit)).between(8, 15)
    if kind == "iban":
        return _mod97(hit)
    if kind == "secret":
        return hit.rlike("[0-9]")
    return F.lit(True)


def _running(sizes: Column, block: int = 256) -> Column:
    """The sum of all sizes before each one. Blocks are summed first, so that no long array is copied once an element."""
    acc = "struct<at: int, out: array<int>>"

    def before(part: Column, start: Column) -> Column:
        first = F.struct(start.cast("int").alias("at"), F.array().cast("array<int>").alias("out")).cast(acc)
        return F.aggregate(part, first, lambda a, x: F.struct((a["at"] + x).cast("int").alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")).cast(acc))["out"]

    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(sizes) - 1) / block).cast("int")), lambda k: F.slice(sizes, k * block + 1, F.lit(block)))
    totals = F.transform(parts, lambda p: F.aggregate(p, F.lit(0), lambda a, x: (a + x).cast("int")))
    many = F.flatten(F.zip_with(parts, before(totals, F.lit(0)), before))
    return F.when(F.size(sizes) <= block, before(sizes, F.lit(0))).otherwise(many)


def _found(rows: DataFrame, kind: str, text: str, hits: str, name: str) -> DataFrame:
    """rows with `name`: start, end, content and what stands just before, of all matches of a kind."""
    none = "array<struct<start: int, end: int, hit: string, near: string>>"
    pieces = F.zip_with(F.slice(F.split(text, PATTERNS[kind], -1), 1, F.size(hits)), F.col(hits), lambda p, h: F.struct(F.length(p).alias("gap"), F.length(h).alias("size"), h.alias("hit"), F.lower(F.right(p, F.lit(REACH))).alias("near")))
    rows = rows.withColumn(name, F.when(F.size(hits) > 0, pieces))
    rows = rows.withColumn(f"{name}_from", F.when(F.size(hits) > 0, _running(F.transform(name, lambda m: m["gap"] + m["size"]))))
    placed = F.zip_with(name, f"{name}_from", lambda m, at: F.struct((at + m["gap"]).alias("start"), (at + m["gap"] + m["size"]).alias("end"), m["hit"].alias("hit"), m["near"].alias("near")))
    return rows.withColumn(name, F.coalesce(placed.cast(none), F.array().cast(none)))


def _spanned(docs: DataFrame) -> DataFrame:
    """(row, text, spans): all columns of docs as one struct, so that their names clash with nothing here."""
    found = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    hits = {}
    for kind, pattern in PATTERNS.items():
        hits[kind] = F.regexp_extract_all("text", F.lit(pattern), F.lit(0))
        if kind in NEEDS:
            hits[kind] = F.when(F.instr("text", NEEDS[kind]) > 0, hits[kind]).otherwise(F.array().cast("array<string>"))
    found = found.withColumns({f"hits_{k}": c for k, c in hits.items()})
    for kind in PATTERNS:
        found = _found(found, kind, "text", f"hits_{kind}", f"at_{kind}")

    def spans(kind: str) -> Column:
        sound = F.filter(F.col(f"at_{kind}"), lambda x: _valid(kind, x["hit"]))
        raised = F.least(F.lit(1.0), F.lit(SCORE[kind]) + F.lit(0.2))
        return F.transform(sound, lambda x: F.struct(F.lit(kind).alias("kind"), x["start"].alias("start"), x["end"].alias("end"), F.when(x["near"].rlike(CONTEXT[kind]), raised).otherwise(F.lit(SCORE[kind])).alias("score"))).cast(_SPAN)

    return found.select("row", "text", F.concat(*[spans(k) for k in PATTERNS]).alias("spans"))


def with_spans(docs: DataFrame) -> DataFrame:
    """docs with `_pii`: an array of (kind, start, end, score) by kind, then start; code points, end exclusive. A column of
    docs of that name is replaced; others may have any name."""
    return _spanned(docs).select(*[F.col(f"row.`{c}`").alias(c) for c in docs.columns if c != "_pii"], F.col("spans").alias("_pii"))


def _joined(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def digest(docs: DataFrame) -> DataFrame:
    """Counts and spans of each row of docs(doc_id, text)."""
    rows = with_spans(docs.select("doc_id", "text"))

    def number(kind: str) -> Column:
        return F.size(F.filter("_pii", lambda s: s["kind"] == kind)).cast("long")

    base = F.filter("_pii", lambda s: s["kind"].isin(*BASE))
    return rows.select(
        "doc_id",
        *[number(k).alias(f"n_{k}") for k in PATTERNS],
        F.size("_pii").cast("long").alias("n_spans"),
        F.sha2(_joined(base), 256).alias("base_sha256"),
        _joined(F.col("_pii")).alias("spans"),
        F.concat_ws(",", F.transform("_pii", lambda s: F.format_number(s["score"], 1))).alias("scores"),
    )


def redacted(docs: DataFrame, least: float = 0.0) -> DataFrame:
    """docs with each span of at least that score replaced by its kind in angle brackets; n_chars follows the text.

    Overlapping spans become one cut, under the kind of the first (at one start, of the longest). The text is cut once: the
    pieces between the cuts are found by running sums, each from its own place.
    """
    rows = _spanned(docs)
    wanted = F.array_sort(F.transform(F.filter("spans", lambda s: s["score"] >= least), lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("back"), s["kind"].alias("kind"))))
    rows = rows.withColumn("wanted", wanted).withColumn("reach", F.when(F.size("wanted") > 0, _reached("wanted")))
    # a span that begins inside what the ones before it reach is no cut of its own
    marked = F.zip_with("wanted", "reach", lambda s, r: F.struct(s["start"].alias("start"), s["kind"].alias("kind"), r.alias("before")))
    rows = rows.withColumn("cuts", F.filter(marked, lambda m: m["start"] >= m["before"]))
    whole = F.struct(F.length("text").alias("start"), F.lit("").alias("kind"), F.array_max(F.transform("wanted", lambda s: -s["back"])).alias("before"))
    pieces = F.transform(F.concat(F.col("cuts"), F.array(whole)), lambda m: F.concat(F.substring("text", m["before"] + 1, m["start"] - m["before"]), F.when(m["kind"] == "", "").otherwise(F.concat(F.lit("<"), m["kind"], F.lit(">")))))
    rows = rows.withColumn("done", F.when(F.col("reach").isNotNull(), F.array_join(pieces, "")))
    out = {"text": F.coalesce("done", "row.text")}
    if "n_chars" in docs.columns:
        out["n_chars"] = F.when(F.col("done").isNull(), F.col("row.n_chars")).otherwise(F.length("done").cast(docs.schema["n_chars"].dataType))
    return rows.select(*[out.get(c, F.col(f"row.`{c}`")).alias(c) for c in docs.columns])


def _reached(spans: str, block: int = 256) -> Column:
    """Of spans in order of start: the largest end of those before each one; by blocks, as in _running."""
    acc = "struct<at: int, out: array<int>>"

    def before(part: Column, start: Column) -> Column:
        first = F.struct(start.cast("int").alias("at"), F.array().cast("array<int>").alias("out")).cast(acc)
        return F.aggregate(part, first, lambda a, x: F.struct(F.greatest(a["at"], x).cast("int").alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")).cast(acc))["out"]

    ends = F.transform(spans, lambda s: (-s["back"]).cast("int"))
    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(spans) - 1) / block).cast("int")), lambda k: F.slice(ends, k * block + 1, F.lit(block)))
    many = F.flatten(F.zip_with(parts, before(F.transform(parts, F.array_max), F.lit(0)), before))
    return F.when(F.size(spans) <= block, before(ends, F.lit(0))).otherwise(many)


_PLAIN = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+",
    "card": r"[0-9](?:[ -]?[0-9])+",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
    "iban": PATTERNS["iban"],
    "secret": "(?i:token|api_?key|secret|password) *[=:] *[\"'']?[A-Za-z0-9+/_-]{16,}",
}


def oracle() -> str:
    """The same result in plain SQL, without possessive repeats or look-behinds."""
    luhn = "list_sum(list_transform(range(0, length(dg)), lambda i: CASE WHEN i % 2 = 1 THEN CASE WHEN 2 * CAST(dg[length(dg) - i] AS INT) > 9 THEN 2 * CAST(dg[length(dg) - i] AS INT) - 9 ELSE 2 * CAST(dg[length(dg) - i] AS INT) END ELSE CAST(dg[length(dg) - i] AS INT) END)) % 10 = 0"
    mod97 = "list_reduce(list_transform(string_split(hit[5:] || hit[1:4], ''), lambda c: CASE WHEN c BETWEEN '0' AND '9' THEN ascii(c) - 48 ELSE ascii(c) - 55 END), lambda a, v: (a * (CASE WHEN v > 9 THEN 100 ELSE 10 END) + v) % 97, 0) = 1"
    valid = {
        "email": "true",
        "ip": "len(list_filter(string_split(hit, '.'), lambda p: CAST(p AS DOUBLE) > 255)) = 0",
        "card": f"CASE WHEN length(dg) BETWEEN 16 AND 19 THEN {luhn} ELSE false END",
        "phone": "length(dg) BETWEEN 8 AND 15",
        "iban": mod97,
        "secret": "regexp_matches(hit, '[0-9]')",
    }
    ctes = ["d AS (SELECT doc_id, coalesce(text, '') AS t, row_number() OVER () AS rid FROM documents)"]
    for k, p in _PLAIN.items():
        ctes.append(f"m_{k} AS (SELECT rid, regexp_extract_all(t, '{p}') AS h, regexp_split_to_array(t, '{p}') AS g FROM d WHERE regexp_matches(t, '{p}'))")
        ctes.append(f"u_{k} AS (SELECT rid, i, h[i] AS hit, regexp_replace(h[i], '[^0-9]', '', 'g') AS dg, list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(h[1:i-1], lambda x: length(x))), 0) AS s, lower(right(g[i], {REACH})) AS near FROM (SELECT rid, h, g, unnest(range(1, len(h) + 1)) AS i FROM m_{k}))")
        raised, plain = f"{min(1.0, SCORE[k] + 0.2):.1f}", f"{SCORE[k]:.1f}"
        ctes.append(f"v_{k} AS (SELECT rid, count(*) AS n, string_agg('{k}:' || CAST(s AS BIGINT) || ':' || (CAST(s AS BIGINT) + length(hit)), ',' ORDER BY s) AS j, string_agg(CASE WHEN regexp_matches(near, '{CONTEXT[k]}') THEN '{raised}' ELSE '{plain}' END, ',' ORDER BY s) AS c FROM u_{k} WHERE {valid[k]} GROUP BY rid)")
    joins = " ".join(f"LEFT JOIN v_{k} USING (rid)" for k in PATTERNS)
    counts = ", ".join(f"CAST(coalesce(v_{k}.n, 0) AS BIGINT) AS n_{k}" for k in PATTERNS)
    counts += ", CAST(" + " + ".join(f"coalesce(v_{k}.n, 0)" for k in PATTERNS) + " AS BIGINT) AS n_spans"
    base = "concat_ws(',', " + ", ".join(f"v_{k}.j" for k in BASE) + ")"
    every = "concat_ws(',', " + ", ".join(f"v_{k}.j" for k in PATTERNS) + ")"
    scores = "concat_ws(',', " + ", ".join(f"v_{k}.c" for k in PATTERNS) + ")"
    return f"WITH {', '.join(ctes)} SELECT doc_id, {counts}, sha256({base}) AS base_sha256, {every} AS spans, {scores} AS scores FROM d {joins}"
