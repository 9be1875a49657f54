"""Secret scanning: three fixed kinds by pattern, and random tokens by a battery of randomness tests.

A token is inferred to be in the narrowest of six encodings. Against uniform draws from that alphabet, a chi-squared
test of its letters, a runs test about the middle of the alphabet and a test of serial correlation must all be passed.
Among the tokens that pass, false discoveries are controlled: under the hypothesis of ordinary writing (letters by
their usual frequency, kinds of characters changing seldom) the likelihood ratio in favour of randomness bounds a
p-value, and the step-up rule runs over the tokens of a document with weights in proportion to their lengths.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import sealed, text_or_empty

#: The patterns of the base kinds, with the group whose length counts and the least length.
ASSIGN = r"""(?i:(?:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{32,}"  # leftmost runs are maximal, so shorter ones need not be matched to be dropped
BASE_KINDS = (("assign", ASSIGN, 1, 8), ("access", ACCESS, 0, 16), ("hex", HEX, 0, 32))

#: Encodings from the narrowest, each with its pattern and alphabet.
ENCODINGS = (
    ("hex", "^[0-9a-f]+$", "0123456789abcdef"),
    ("hex_upper", "^[0-9A-F]+$", "0123456789ABCDEF"),
    ("base32", "^[A-Z2-7]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"),
    ("base36", "^[0-9a-z]+$", "0123456789abcdefghijklmnopqrstuvwxyz"),
    ("base36_upper", "^[0-9A-Z]+$", "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    ("base64", "^[A-Za-z0-9+/_-]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/"),
)
#: Usual frequency of the letters a to z, in thousandths.
LETTER_PERMILLE = (82, 15, 28, 43, 127, 22, 20, 61, 70, 2, 8, 40, 24, 67, 75, 19, 1, 60, 63, 91, 28, 10, 24, 2, 20, 1)

#: A token may follow "=": that sign belongs to it as padding only, at its end. Tokens that touch a base span are none.
TOKEN = r"(?<![A-Za-z0-9+/_﷐-﷯-])[A-Za-z0-9+/_-]{20,}+(?![﷐-﷯])(?:={1,2}(?![A-Za-z0-9+/_=﷐-﷯-]))?"
MASK = "[SECRET]"
SPAN = "struct<s:int,k:int,e:int,kind:string>"


def _sql(s: str) -> str:
    return s.replace("\\", "\\\\").replace("'", "\\'")


def _located(t: str, pattern: str, group: int, least: int, kind: str, rank: int) -> Column:
    """``struct(m, g, p, s)`` for a pattern in column ``t``: matches, their group, the text between, and the starts in code
    points. Starts are running sums, made block by block, with as many blocks as a block has matches."""
    p = _sql(pattern)
    running = "aggregate({xs}, struct({start} as at, cast(array() as array<int>) as out), (a, x) -> struct(a.at + {step} as at, array_append(a.out, a.at) as out), a -> a.out)"
    inner = running.format(xs="slice(z.n, b * z.w + 1, z.w)", start="z.o[b]", step="x")
    offsets = running.format(xs="z.sums", start="0", step="x")
    found = f"""
      transform(transform(transform(transform(array(struct(regexp_extract_all({t}, '{p}', 0) as m, regexp_extract_all({t}, '{p}', {group}) as g, split({t}, '{p}', -1) as p)),
        z -> struct(z.m as m, z.g as g, z.p as p, transform(z.m, (x, i) -> length(z.p[i]) + length(x)) as n, cast(ceil(sqrt(size(z.m))) as int) as w)),
        z -> struct(z.m as m, z.g as g, z.p as p, z.n as n, z.w as w, transform(sequence(0, (size(z.m) - 1) div z.w), b -> aggregate(slice(z.n, cast(b * z.w + 1 as int), z.w), 0, (a, x) -> a + x)) as sums)),
        z -> struct(z.m as m, z.g as g, z.p as p, z.n as n, z.w as w, size(z.sums) as c, {offsets} as o)),
        z -> struct(z.m as m, z.g as g, z.p as p, transform(flatten(transform(sequence(0, z.c - 1), b -> {inner.replace("b * z.w + 1", "cast(b * z.w + 1 as int)")})), (x, i) -> x + length(z.p[i])) as s))[0]"""
    return F.expr(f"case when {t} rlike '{p}' then {found} end")


def _spans(z: str, least: int, kind: str, rank: int) -> str:
    """SQL array of the spans of located matches whose group is long enough."""
    all_ = f"transform({z}.m, (x, i) -> case when length({z}.g[i]) >= {least} then struct({z}.s[i] as s, {rank} as k, {z}.s[i] + length(x) as e, '{kind}' as kind) end)"
    return f"coalesce(filter({all_}, x -> x is not null), cast(array() as array<{SPAN}>))"


def _blanked(t: str, z: str, keep: str) -> str:
    """SQL of a text with its matches overwritten, place for place, by the fill, but for those that ``keep`` holds of."""
    return f"case when {z} is null then {t} else array_join(transform({z}.p, (x, i) -> case when i >= size({z}.m) then x when {keep} then concat(x, {z}.m[i]) else concat(x, repeat(fill, length({z}.m[i]))) end), '') end"


def _randomness(tok: str) -> str:
    """SQL of ``struct(passed, p, n)`` for a token (padding removed): verdict of the battery, bound on the p-value."""
    enc = "case " + " ".join(f"when {tok} rlike '{rx}' then '{abc}'" for _, rx, abc in ENCODINGS) + " end"
    freq = "array(" + ", ".join(f"{x / 1000}D" for x in LETTER_PERMILLE) + ")"
    tail = lambda z: f"(1 / (1 + exp(least(1.5976D * ({z}) + 0.070565992D * pow({z}, 3), 600D))))"
    chars = f"regexp_extract_all({tok}, '.', 0)"
    return f"""
      transform(transform(transform(transform(array(struct({enc} as abc, {chars} as c)),
        x -> struct(x.abc as abc, x.c as c, size(x.c) as n, length(x.abc) as k,
          transform(x.c, y -> case when y = '-' and not contains(x.abc, '-') then 62 when y = '_' then 63 else locate(y, x.abc) - 1 end) as v)),
        x -> struct(x.n as n, x.k as k, x.c as c, x.v as v,
          aggregate(x.v, 0D, (a, y) -> a + y) / x.n as mean,
          size(filter(x.v, y -> 2 * y >= x.k)) as up,
          1 + size(filter(x.v, (y, i) -> i > 0 and (2 * y >= x.k) <> (2 * x.v[greatest(i - 1, 0)] >= x.k))) as runs,
          aggregate(array_distinct(x.v), 0D, (a, u) -> a + pow(size(filter(x.v, y -> y = u)), 2)) as squares)),
        x -> struct(x.n as n, x.c as c, x.k as k,
          (x.k * x.squares / x.n - x.n - (x.k - 1)) / sqrt(2D * (x.k - 1) * (x.n - 1) / x.n) as z_chi,
          case when x.up = 0 or x.up = x.n then 9D else abs((x.runs - (2D * x.up * (x.n - x.up) / x.n + 1))
            / sqrt(greatest(2D * x.up * (x.n - x.up) * (2D * x.up * (x.n - x.up) - x.n) / (pow(x.n, 2) * (x.n - 1)), 1e-6D))) end as z_runs,
          case when aggregate(x.v, 0D, (a, y) -> a + pow(y - x.mean, 2)) = 0 then 9D else abs(sqrt(x.n - 1) * (1D / (x.n - 1)
            + aggregate(sequence(1, x.n - 1), 0D, (a, i) -> a + (x.v[i] - x.mean) * (x.v[i - 1] - x.mean))
            / aggregate(x.v, 0D, (a, y) -> a + pow(y - x.mean, 2)))) end as z_serial)),
        x -> struct(
          x.n as n,
          3 * least({tail("x.z_chi")}, 2 * {tail("x.z_runs")}, 2 * {tail("x.z_serial")}) > 0.001D as passed,
          least(1D, pow(2D, -greatest(-900D, least(900D, aggregate(sequence(0, x.n - 1), 0D, (a, i) -> a
            - log2(x.k)
            - log2(case when x.c[i] rlike '[0-9]' then 0.1D when x.c[i] rlike '[A-Za-z]' then {freq}[ascii(lower(x.c[i])) - 97] else 0.5D end)
            - log2(case when i = 0 then 0.25D
              when translate(x.c[i], 'abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789', '{"a" * 26}{"A" * 26}{"0" * 10}')
                 = translate(x.c[greatest(i - 1, 0)], 'abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789', '{"a" * 26}{"A" * 26}{"0" * 10}')
              then 0.85D else 0.05D end)))))) as p))[0]"""


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", false_discovery: float = 0.01) -> DataFrame:
    """All columns of ``docs`` as ``struct row``, with ``t`` (text), ``base`` and ``spans``: arrays of ``struct(s, k, e, kind)``,
    and ``marked``: the text with every span overwritten by the character ``fill``, which the text does not hold.

    ``s`` and ``e`` count code points, ``e`` exclusive; arrays are ordered by start, then kind (assign, access, hex,
    random). A null text counts as empty and has no spans; repeated rows stay repeated; an empty table stays empty.
    Work grows about with the length of a text, and with the 1.5th power of its number of matches.
    """
    own = docs.select(F.struct("*").alias("row"), text_or_empty(F.col(text_col)).alias("t"))
    fills = "array(" + ", ".join(f"'{chr(0xFDD0 + i)}'" for i in range(32)) + ")"
    own = own.withColumn("fill", F.expr(f"case when t rlike '[\\\\uFDD0-\\\\uFDEF]' then coalesce(filter({fills}, f -> not contains(t, f))[0], '{chr(0xFDD0)}') else '{chr(0xFDD0)}' end"))
    blank, names = "t", []
    for i, (kind, rx, group, least) in enumerate(BASE_KINDS):
        own = own.withColumn(f"z{i}", _located("t", rx, group, least, kind, i))
        names.append(f"case when z{i} is null then cast(array() as array<{SPAN}>) else {_spans(f'z{i}', least, kind, i)} end")
    for i, (_, rx, group, least) in enumerate(BASE_KINDS):
        # a later kind is looked for in the text blanked before; what is left of its match there touches a blank
        again = f"z{i}" if not i else f"y{i}"
        if i:
            some = " or ".join(f"z{j} is not null" for j in range(i))
            struct = f"struct(regexp_extract_all(blank, '{_sql(rx)}', 0) as m, regexp_extract_all(blank, '{_sql(rx)}', {group}) as g, split(blank, '{_sql(rx)}', -1) as p)"
            own = own.withColumn(again, F.expr(f"case when z{i} is null then null when {some} then {struct} else struct(z{i}.m as m, z{i}.g as g, z{i}.p as p) end"))
        own = own.withColumn("blank", F.expr(_blanked(blank, again, f"length({again}.g[i]) < {least}")))
        blank = "blank"
    own = own.select("row", "t", "fill", "blank", F.array_sort(F.expr(f"concat({', '.join(names)})")).alias("base"))
    own = own.withColumn("cand", _located("blank", TOKEN, 0, 20, "random", len(BASE_KINDS)))
    own = own.withColumn("test", F.expr(f"transform(cand.m, c -> {_randomness('rtrim(chr(61), c)')})"))
    weighed = "transform(array(aggregate(test, 0D, (a, y) -> a + y.n) / size(test)), w -> transform(test, x -> x.p * w / x.n))[0]"
    own = own.withColumn("q", F.expr(f"case when size(test) > 0 then {weighed} end"))
    # the step-up rule: the greatest weighed p-value that its rank allows
    most = f"array_max(transform(array_sort(q), (x, i) -> case when x <= {false_discovery}D * (i + 1) / size(q) then x end))"
    # bound to a variable, so that no optimiser writes the rule into the lambda that it is compared in
    own = own.withColumn("hit", F.expr(f"transform(array(struct(test, q, {most} as most)), z -> transform(z.test, (x, i) -> x.passed and coalesce(z.q[i] <= z.most, false)))[0]"))
    k = len(BASE_KINDS)
    added = f"filter(transform(cand.m, (x, i) -> case when hit[i] then struct(cand.s[i] as s, {k} as k, cand.s[i] + length(x) as e, 'random' as kind) end), x -> x is not null)"
    spans = F.array_sort(F.expr(f"concat(base, coalesce({added}, cast(array() as array<{SPAN}>)))"))
    marked = F.expr(_blanked("blank", "cand", "not hit[i]"))
    return sealed(own, ["row", "t", "fill"], {"base": F.col("base"), "spans": spans, "marked": marked})


def span_text(spans: str) -> Column:
    return F.expr(f"array_join(transform({spans}, x -> concat(x.kind, ':', x.s, ':', x.e)), ',')")


def secret_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id``, counts of the base kinds, the digest of the base spans, and all spans, for every row."""
    found = find_secrets(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")))
    n = {kind: F.expr(f"cast(size(filter(base, x -> x.kind = '{kind}')) as bigint)").alias(f"n_{kind}") for kind, *_ in BASE_KINDS}
    return found.select(F.col("row.doc_id").alias("doc_id"), *n.values(), F.sha2(span_text("base"), 256).alias("base_sha256"), span_text("spans").alias("spans"))


def redact(docs: DataFrame, text_col: str = "text", mask: str = MASK) -> DataFrame:
    """``docs`` with the same columns, each span in the text replaced by a mask; overlapping and touching spans become one.

    A null text stays null.
    """
    found = find_secrets(docs, text_col=text_col)
    text = F.expr(f"case when size(spans) = 0 then t else regexp_replace(marked, concat(fill, '+'), '{_sql(mask)}') end")
    kept = [F.when(F.col(f"row.`{text_col}`").isNotNull(), text).alias(c) if c == text_col else F.col(f"row.`{c}`").alias(c) for c in docs.columns]
    return found.select(*kept)
