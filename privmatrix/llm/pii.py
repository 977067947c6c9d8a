"""Personal data in texts, with DataFrame functions only.

Regular expressions propose spans, validators (number ranges, Luhn, mod-97) confirm them, and context words standing
shortly before a span raise its score. Offsets count code points, ends are exclusive.

Nulls and empty texts have no spans. Every span is judged on its own, so repeated rows get the same spans and ties cannot
arise; spans of different kinds may overlap. Extra input columns are kept by ``find`` and ``redact``; a column named like
an output column is replaced.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CONTEXT_CHARS = 48
RUN = 64


@dataclass(frozen=True)
class Kind:
    """pattern: as published; quick: the same matches, written so that Java's matcher never rescans a run or recurses."""

    name: str
    pattern: str
    quick: str
    needs: str
    score: int
    context: str
    bonus: int = 10  # for a context word
    least: int = 0  # a span of a lower score is dropped


#: The patterns of the first four kinds are given; the others are the grouped form of account numbers and hexadecimal
#: secrets, which only count after a word that announces one.
KINDS = (
    Kind("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++", "@", 90, "mail|contact|write|kontakt|correo|courriel"),
    Kind("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++", ".", 70, r"\bip\b|host|server|address|adresse"),
    Kind("card", r"[0-9]([\x20-]?[0-9])+", r"[0-9](?:[\x20-]?[0-9])++", "", 80, "card|visa|credit|karte|carte|tarjeta"),
    Kind("phone", r"\+[0-9][\x20().0-9-]+[0-9]", r"\+[0-9][\x20().0-9-]+[0-9]", "+", 60, "call|phone|tel|mobile|fax"),
    Kind("iban", r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?", r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?", "", 95, "iban|account|bank|konto|compte|cuenta"),
    Kind("secret", r"[0-9A-Fa-f]{32,64}", r"[0-9A-Fa-f]{32,64}", "", 40, "token|secret|password|passwort|api.?key", 50, 60),
)
BASE_KINDS = ("email", "ip", "card", "phone")


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _confirmed(kind: str, x: Column) -> Column:
    digits = F.regexp_replace(x, "[^0-9]", "")
    n = F.length(digits)
    if kind == "ip":
        part = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
        return x.rlike(rf"^(?:{part}\.){{3}}{part}$")
    if kind == "card":
        total = F.aggregate(F.sequence(F.lit(1), n), F.lit(0), lambda acc, i: acc + _luhn_digit(F.substring(digits, n - i + 1, F.lit(1)).cast("int"), i))
        return F.when(n.between(14, 19), total % 10 == 0).otherwise(False)
    if kind == "phone":
        return n.between(10, 15)
    if kind == "iban":
        plain = F.replace(x, F.lit(" "), F.lit(""))
        turned = F.concat(F.substring(plain, F.lit(5), F.length(plain)), F.substring(plain, F.lit(1), F.lit(4)))
        signs = F.lit("0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ")
        rest = F.aggregate(F.sequence(F.lit(1), F.length(turned)), F.lit(0), lambda acc, i: _mod97(acc, F.instr(signs, F.substring(turned, i, F.lit(1))) - 1))
        return F.length(plain).between(15, 34) & (rest == 1)
    if kind == "secret":
        return x.rlike("[0-9]") & x.rlike("[A-Fa-f]")
    return F.lit(True)


def _luhn_digit(d: Column, i: Column) -> Column:
    return F.when(i % 2 == 1, d).when(d > 4, d * 2 - 9).otherwise(d * 2)


def _mod97(acc: Column, value: Column) -> Column:
    return F.when(value < 10, acc * 10 + value).otherwise(acc * 100 + value) % 97


def _placed(matches: str, parts: str, order: int, kind: Kind) -> Column:
    """Spans of one kind from its matches and the texts between them. Offsets are summed by runs of ``RUN`` matches, then within each run, so that no
    list grows with all matches of a text one by one."""
    placed = F.expr(f"""
        transform(array(zip_with({matches}, slice({parts}, 1, size({matches})), (x, gap) -> named_struct('gap', length(gap), 'len', length(x), 'text', x,
            'before', substring(gap, greatest(length(gap) - {CONTEXT_CHARS - 1}, 1), {CONTEXT_CHARS})))), all ->
          transform(array(transform(sequence(0, (size(all) - 1) div {RUN}), k -> slice(all, cast(k * {RUN} + 1 as int), {RUN}))), runs ->
            flatten(zip_with(runs,
              slice(aggregate(runs, array(0), (acc, run) -> concat(acc, array(element_at(acc, -1) + aggregate(run, 0, (n, x) -> n + x.gap + x.len)))), 1, size(runs)),
              (run, first) -> aggregate(run, named_struct('at', first, 'out', cast(array() as array<struct<start: int, stop: int, text: string, before: string>>)),
                (acc, x) -> named_struct('at', acc.at + x.gap + x.len, 'out', concat(acc.out, array(named_struct('start', acc.at + x.gap, 'stop', acc.at + x.gap + x.len, 'text', x.text, 'before', x.before)))),
                acc -> acc.out))))[0])[0]""")
    kept = F.filter(placed, lambda x: _confirmed(kind.name, x["text"]))
    near = f"(?i)(?:{kind.context})"
    scored = F.transform(kept, lambda x: F.struct(x["start"].alias("start"), F.lit(order).alias("order"), x["stop"].alias("stop"), F.lit(kind.name).alias("kind"), (F.lit(kind.score) + F.when(x["before"].rlike(near), kind.bonus).otherwise(0)).alias("score")))
    return F.filter(scored, lambda x: x["score"] >= kind.least) if kind.least else scored


def find(df: DataFrame, text_col: str = "text", out: str = "spans", kinds: tuple[Kind, ...] = KINDS) -> DataFrame:
    """``df`` with ``out``: array<struct<start, order, stop, kind, score>> by start, then kind as listed."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    none = F.expr("cast(array() as array<string>)")
    step = df.drop(out)
    for k in kinds:
        found = F.regexp_extract_all(text, F.lit(k.quick), 0)
        step = step.withColumn(f"__m_{k.name}", F.when(F.instr(text, k.needs) > 0, found).otherwise(none) if k.needs else found)
    for k in kinds:
        step = step.withColumn(f"__p_{k.name}", F.when(F.size(f"__m_{k.name}") > 0, F.split(text, k.quick, -1)).otherwise(none))
    spans = F.concat(*[_placed(f"__m_{k.name}", f"__p_{k.name}", i, k) for i, k in enumerate(kinds)])
    step = step.withColumn(out, F.sort_array(spans))
    return step.drop(*[f"__{side}_{k.name}" for k in kinds for side in "mp"])


def _count(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda x: x["kind"] == kind)).cast("long")


def listed(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["stop"].cast("string"))), ",")


def digest(df: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: counts by kind, the hash of the base spans, all spans and their scores."""
    found = find(df.select(id_col, text_col), text_col, "__spans").select(id_col, "__spans")
    spans = F.col("__spans")
    base = F.filter(spans, lambda x: x["kind"].isin(*BASE_KINDS))
    counts = [_count(spans, k.name).alias(f"n_{k.name}") for k in KINDS]
    return found.select(id_col, *counts, F.sha2(listed(base), 256).alias("base_sha256"), listed(spans).alias("spans"), F.array_join(F.transform(spans, lambda x: x["score"].cast("string")), ",").alias("scores"))


def redact(df: DataFrame, text_col: str = "text") -> DataFrame:
    """``df`` with every span replaced by its kind in square brackets; of overlapping spans the text from the first start to the last end goes once."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    found = find(df, text_col, "__spans")
    pieces = F.aggregate(
        "__spans",
        F.expr("named_struct('at', 0, 'out', cast(array() as array<string>))"),
        lambda acc, x: F.struct(
            F.greatest(acc["at"], x["stop"]).alias("at"),
            F.when(x["start"] >= acc["at"], F.concat(acc["out"], F.array(F.substring(text, acc["at"] + 1, x["start"] - acc["at"]), F.concat(F.lit("["), x["kind"], F.lit("]"))))).otherwise(acc["out"]).alias("out"),
        ),
        lambda acc: F.concat(acc["out"], F.array(F.substring(text, acc["at"] + 1, F.length(text)))),
    )
    return found.withColumn(text_col, F.when(F.size("__spans") > 0, F.array_join(pieces, "")).otherwise(F.col(text_col))).drop("__spans").select(df.columns)


def oracle() -> str:
    """DuckDB SQL for ``digest`` over documents."""
    parts, columns = [], []
    for i, k in enumerate(KINDS):
        test = {
            "email": "true",
            "ip": "list_aggregate([length(ltrim(y, '0')) <= 3 AND (CASE WHEN length(ltrim(y, '0')) <= 3 THEN cast('0' || ltrim(y, '0') AS INTEGER) ELSE 999 END) <= 255 FOR y IN string_split(x, '.')], 'bool_and')",
            "card": "length(regexp_replace(x, '[^0-9]', '', 'g')) BETWEEN 14 AND 19 AND list_sum([(CASE WHEN p % 2 = 1 THEN d WHEN d > 4 THEN d * 2 - 9 ELSE d * 2 END) FOR d, p IN list_reverse([cast(c AS INTEGER) FOR c IN string_split(regexp_replace(x, '[^0-9]', '', 'g'), '')])]) % 10 = 0",
            "phone": "length(regexp_replace(x, '[^0-9]', '', 'g')) BETWEEN 10 AND 15",
            "iban": "length(replace(x, ' ', '')) BETWEEN 15 AND 34 AND list_reduce(list_prepend(0, [instr('0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ', c) - 1 FOR c IN string_split(substring(replace(x, ' ', ''), 5) || substring(replace(x, ' ', ''), 1, 4), '')]), lambda a, b: ((CASE WHEN b < 10 THEN a * 10 ELSE a * 100 END) + b) % 97) = 1",
            "secret": "regexp_matches(x, '[0-9]') AND regexp_matches(x, '[A-Fa-f]')",
        }[k.name]
        pattern = k.pattern.replace("'", "''").replace("(\\.", "(?:\\.").replace("([\\x20-]", "(?:[\\x20-]")
        parts.append(f"""SELECT * FROM (SELECT doc_id, {i} AS o, '{k.name}' AS kind, start, start + len(x) AS stop, {k.score} + (CASE WHEN regexp_matches(right(gap, {CONTEXT_CHARS}), '(?i)(?:{k.context})') THEN {k.bonus} ELSE 0 END) AS score
          FROM (SELECT doc_id, m[i] AS x, p[i] AS gap, cast(coalesce(list_sum([length(y) FOR y IN p[:i]]), 0) + coalesce(list_sum([length(y) FOR y IN m[:i - 1]]), 0) AS BIGINT) AS start
            FROM (SELECT doc_id, m, p, unnest(range(1, len(m) + 1)) AS i FROM (SELECT doc_id, regexp_extract_all(t, '{pattern}') AS m, string_split_regex(t, '{pattern}') AS p FROM d))) WHERE {test}) WHERE score >= {k.least}""")
        columns.append(f"cast(count(*) FILTER (WHERE kind = '{k.name}') AS BIGINT) AS n_{k.name}")
    span = "kind || ':' || start || ':' || stop"
    base = ", ".join(f"'{k}'" for k in BASE_KINDS)
    return f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), s AS ({" UNION ALL ".join(parts)})
      SELECT d.doc_id, {", ".join(columns)}, sha256(coalesce(string_agg({span}, ',' ORDER BY start, o) FILTER (WHERE kind IN ({base})), '')) AS base_sha256,
        coalesce(string_agg({span}, ',' ORDER BY start, o), '') AS spans, coalesce(string_agg(cast(score AS VARCHAR), ',' ORDER BY start, o), '') AS scores
      FROM d LEFT JOIN s USING (doc_id) GROUP BY d.doc_id"""
