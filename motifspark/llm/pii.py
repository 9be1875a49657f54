"""Personal data replaced by keyed surrogates of the same type and shape.

Entities are found by one alternation of patterns, so matches never overlap. Equal entities get equal surrogates in every
document. Numbers, addresses and mails are mapped by a keyed permutation of all values of their own format: distinct by
construction, never equal to the original, however crowded the format is, and check digits stay as right or wrong
as they were. Names are mapped word by word, so ``Mr. Smith``, ``Mr. John Smith``, ``SMITH`` and a later bare
``Smith`` agree; a given name follows the gender of the title, every word its script and case. Names grow out of
syllables: surrogates of all distinct words of the corpus are compared with one another and with the words
themselves, and a word whose surrogate clashes gets one syllable more until all are distinct. Only documents with
names are joined with these words, all others are rewritten in the scan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import durable, sized_broadcast, text_or_empty

#: Titles, name particles and patterns, in the order in which they are tried at a place.
TITLES_M = "Mr|Herr|Monsieur|Señor|Sr|господин|г-н|κύριος"
TITLES_F = "Mrs|Ms|Miss|Frau|Madame|Mme|Señora|Sra|Mademoiselle|госпожа|г-жа|κυρία"
TITLES_N = "Dr|Prof"
PARTICLES = "von|van|zu|zum|zur|der|den|de|du|des|del|della|di|da|dos|la|le|el|al|bin|ibn|ter|ten|af|av"


def _both_cases(titles: str) -> str:
    return "|".join(dict.fromkeys(x for t in titles.split("|") for x in (t, t.upper())))


_TITLE = rf"(?:{_both_cases(f'{TITLES_M}|{TITLES_F}|{TITLES_N}')})(?:\.\s{{0,2}}|\s{{1,2}})"
_WORD = r"(?:\p{Ll}['’])?[\p{Lu}\p{Lt}\p{Lo}][\p{L}\p{M}]*(?:['’-]\p{L}[\p{L}\p{M}]*)*"
_PART = rf"(?:(?:{PARTICLES})\s)*(?:\p{{Lu}}\.\s?)*{_WORD}"
PATTERNS = (
    ("email", r"[\p{L}\p{N}][\p{L}\p{N}._+-]*@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+)*\.\p{L}{2,}"),
    ("iban", r"(?<![\p{L}\p{N}])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])"),
    ("ip", r"(?<![\p{N}.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?!\.?\p{N})"),
    ("ssn", r"(?<![\p{N}-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\p{N}-])"),
    ("card", r"(?<![\p{L}\p{N}])[0-9](?:[ -]?[0-9]){12,18}(?![\p{L}\p{N}])"),
    ("phone", r"(?<![\p{L}\p{N}])(?:\+[0-9]{1,3}[ .-]?)?\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}(?!\p{N})|(?<!\p{N})\+[0-9]{1,3}(?:[ .-]?[0-9]{2,4}){2,5}(?!\p{N})|(?<![\p{N}-])[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}(?![\p{N}-])"),
    ("name", rf"(?<!\p{{L}}){_TITLE}{_PART}(?:\s{_PART}){{0,2}}(?!\p{{L}})"),
)
#: The words of a name: runs of letters, with the prefixes Mc and Mac apart.
WORDS = r"(?:Mc|Mac)(?=\p{Lu})|[\p{L}\p{M}]+"

#: Code points (first, last, step) within which a character is exchanged for another.
RANGES = (
    (0x30, 0x39, 1), (0x41, 0x5A, 1), (0x61, 0x7A, 1), (0xC0, 0xD6, 1), (0xD8, 0xDE, 1), (0xE0, 0xF6, 1), (0xF8, 0xFF, 1), (0x101, 0x137, 2),
    (0x13A, 0x148, 2), (0x14B, 0x177, 2), (0x391, 0x3A1, 1), (0x3A3, 0x3A9, 1), (0x3B1, 0x3C1, 1), (0x3C3, 0x3C9, 1), (0x410, 0x42F, 1), (0x430, 0x44F, 1),
    (0x450, 0x45F, 1), (0x5D0, 0x5EA, 1), (0x621, 0x63A, 1), (0x641, 0x64A, 1), (0x904, 0x939, 1), (0xE01, 0xE2E, 1), (0x3041, 0x3096, 1), (0x30A1, 0x30FA, 1),
    (0x4E00, 0x9FFF, 1), (0xAC00, 0xD7A3, 1),
)
#: The stock of names by script: 32 syllables, capitals for initials, and eight endings a role.
STOCK = {
    "latin": {
        "syllables": "ba ben dal der far fen gar gol hal hin jor kal kem lan lor mar min nal nor pel ran ros sal sen tal tor ul van vel wen bri dro",
        "initials": "ABCDEFGHIJKLMNOPQRSTUVWXYZ",
        "family": "mann son ley ton er ing feld berg",
        "given_m": "o an us in ert ard win rik",
        "given_f": "a ia ina ella ana etta ita ika",
        "given_n": "e y is ix ay ine el ou",
    },
    "cyrillic": {
        "syllables": "ба бен вал вер га гор дал дор жар зел зин кал кор лан лор мар мил нал нор пел пол ран рос сал сен тал тор фен хар чер шан юл",
        "initials": "АБВГДЕЖЗИКЛМНОПРСТУФХЦЧШЭЮЯ",
        "family": "енко ук ич ских ян дзе швили ко",
        "given_m": "ан ей ил ор ий ислав ил им",
        "given_f": "а ия ина ана ела ника ая ета",
        "given_n": "и е ис эль ай у ен ри",
    },
    "greek": {
        "syllables": "αλ βαρ βελ γαλ γορ δαλ δορ ζαν ζελ ημ θαλ θεο καλ κορ λαμ λορ μαν μελ ναλ νορ ξεν παλ παρ ραν ροδ σαλ στα ταλ τορ φαν χαρ ψαλ",
        "initials": "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ",
        "family": "ιδης ακης οπουλος ου ατος ελης αρης ιου",
        "given_m": "ος ης ας ων ιος ανος εας ιππος",
        "given_f": "α η ια ινα ουλα ανα ιδα ιτσα",
        "given_n": "ι υ ις ω ει αι ον εν",
    },
}
ROUNDS = 4

_ANY = "|".join(f"(?:{p})" for _, p in PATTERNS)
_HINT = rf"[0-9@]|{_TITLE}"


def _sql(s: str) -> str:
    return s.replace("\\", "\\\\").replace("'", "\\'")


def _kind(m: str) -> str:
    return "case " + " ".join(f"when {m} rlike '{_sql(f'^(?:{p})$')}' then '{k}'" for k, p in PATTERNS) + " end"


def _normal(m: str, kind: str) -> str:
    """The form in which two mentions are the same entity."""
    digits = f"regexp_replace({m}, '[^0-9]+', '')"
    return f"case when {kind} in ('card', 'phone', 'ssn') then {digits} when {kind} = 'iban' then replace({m}, ' ', '') when {kind} = 'email' then lower({m}) else {m} end"


def _chars(s: str) -> str:
    return f"transform(sequence(1, length({s})), q -> substring({s}, q, 1))"


def _units(n: str, kind: str) -> str:
    """SQL array of ``struct(at, lo, step, size, v)``: the exchangeable characters of a normal form (octets of an address),
    their place, range and value. A phone number keeps its first digit, an IBAN its country."""
    ranges = "array(" + ", ".join(f"struct({lo} as lo, {(hi - lo) // step + 1} as size, {step} as step)" for lo, hi, step in RANGES) + ")"
    found = f"""flatten(transform({_chars(n)}, (c, i) -> transform(filter({ranges}, r -> ascii(c) >= r.lo and ascii(c) < r.lo + r.size * r.step and (ascii(c) - r.lo) % r.step = 0),
        r -> struct(i as at, r.lo as lo, r.step as step, r.size as size, cast((ascii(c) - r.lo) div r.step as int) as v))))"""
    last = f"length({n}) - locate('.', reverse({n}))"
    allowed = f"case {kind} when 'email' then u.at < {last} when 'iban' then u.at >= 4 when 'phone' then u.at >= 1 when 'card' then u.at < length({n}) - 1 else true end"
    base = "case when length(o) = 1 then 0 when length(o) = 2 and o < '10' then 0 when length(o) = 2 then 10 when o < '100' then 0 when o < '256' then 100 else 256 end"
    size = "case when length(o) = 1 then 10 when length(o) = 2 and o < '10' then 10 when length(o) = 2 then 90 when o < '100' then 100 when o < '256' then 156 else 744 end"
    octets = f"transform(split({n}, '[.]'), (o, i) -> struct(i as at, {base} as lo, 1 as step, {size} as size, cast(o as int) - {base} as v))"
    return f"case when {kind} = 'ip' then {octets} else filter({found}, u -> {allowed}) end"


def _permuted(u: str, tag: str) -> str:
    """SQL array of the new values of units: a keyed permutation of all values that units of these ranges can have.

    Rounds add a keyed stream, made of one half, to the other half; the first value is then moved on by a keyed step,
    and the rounds are undone. As a conjugate of a move it maps different values to different ones and none to itself.
    """
    half = f"(size({u}) div 2)"
    seed = f"concat({tag}, '|', i, '|', array_join(case when i % 2 = 0 then slice(a, {half} + 1, size(a)) else slice(a, 1, {half}) end, ','))"
    byte = "cast(conv(substring(s, 1 + 4 * (j % 32), 4), 16, 10) as int)"

    def rounds(start: str, order: str, sign: str) -> str:
        moved = f"transform(a, (e, j) -> case when (j < {half}) = (i % 2 = 0) then pmod(e {sign} {byte}, {u}[j].size) else e end)"
        return f"aggregate({order}, {start}, (a, i) -> transform(array(concat(sha2({seed}, 256), sha2(concat('+', {seed}), 256))), s -> {moved})[0])"

    there = rounds(f"transform({u}, y -> y.v)", f"sequence(0, {ROUNDS - 1})", "+")
    step = f"(1 + cast(conv(substring(sha2(concat({tag}, '|step'), 256), 1, 6), 16, 10) as int) % ({u}[0].size - 1))"
    moved = f"transform({there}, (e, j) -> case when j = 0 then (e + {step}) % {u}[0].size else e end)"
    return rounds(moved, f"sequence({ROUNDS - 1}, 0, -1)", "-")


def _luhn(s: str) -> str:
    """SQL of the check digit that a number without its last digit asks for."""
    one = f"cast(substring({s}, -j - 1, 1) as int)"
    total = f"aggregate(sequence(1, length({s}) - 1), 0, (a, j) -> a + case when j % 2 = 0 then {one} else cast((2 * {one}) div 10 as int) + (2 * {one}) % 10 end)"
    return f"(10 - {total} % 10) % 10"


def _iban_check(s: str) -> str:
    """SQL of the two check digits that country and account of an IBAN ask for, as a number."""
    value = "case when c between '0' and '9' then a * 10 + cast(c as int) else a * 100 + ascii(c) - 55 end"
    return f"(98 - aggregate({_chars(f'concat(substring({s}, 5), substring({s}, 1, 2), {chr(39)}00{chr(39)})')}, 0, (a, c) -> ({value}) % 97))"


def _surrogate(m: str, kind: str, norm: str, key: str) -> str:
    """SQL of the surrogate of a mention that is no name."""
    pattern = "array_join(transform(x.u, y -> concat(y.at, ':', y.lo, ':', y.size)), ',')"
    w = _permuted("x.u", f"concat('{_sql(key)}', '|', x.k, '|', length(x.n), '|', {pattern})")
    char = "decode(unhex(lpad(hex(x.u[p - 1].lo + x.u[p - 1].step * x.w[p - 1]), 4, '0')), 'UTF-16BE')"
    fresh = f"array_join(transform({_chars('x.n')}, (c, i) -> transform(array(cast(array_position(transform(x.u, y -> y.at), i) as int)), p -> case when p > 0 then {char} else c end)[0]), '')"
    octets = "array_join(transform(split(x.n, '[.]'), (o, i) -> lpad(cast(x.u[i].lo + x.w[i] as string), length(o), '0')), '.')"
    card = f"concat(substring(x.s, 1, length(x.s) - 1), cast(({_luhn('x.s')} + 10 + cast(substring(x.n, -1, 1) as int) - {_luhn('x.n')}) % 10 as string))"
    iban = f"concat(substring(x.s, 1, 2), lpad(cast(({_iban_check('x.s')} + 100 + cast(substring(x.n, 3, 2) as int) - {_iban_check('x.n')}) % 100 as string), 2, '0'), substring(x.s, 5))"
    # back into the format of the mention: the places are those among its digits, or its characters but spaces
    place = "length(regexp_replace(substring(x.m, 1, i + 1), '[^0-9]+', ''))"
    numbers = f"array_join(transform({_chars('x.m')}, (c, i) -> case when c between '0' and '9' then substring(x.s, {place}, 1) else c end), '')"
    spaced = f"array_join(transform({_chars('x.m')}, (c, i) -> case when c = ' ' then c else substring(x.s, length(replace(substring(x.m, 1, i + 1), ' ', '')), 1) end), '')"
    cased = f"case when length(x.m) <> length(x.s) then x.s else array_join(transform({_chars('x.m')}, (c, i) -> case when c = lower(c) then substring(x.s, i + 1, 1) else upper(substring(x.s, i + 1, 1)) end), '') end"
    return f"""transform(transform(transform(transform(array(struct({m} as m, {kind} as k, {norm} as n, {_units(norm, kind)} as u)),
        x -> struct(x.m as m, x.k as k, x.n as n, x.u as u, case when size(x.u) = 0 then array() else {w} end as w)),
        x -> struct(x.m as m, x.k as k, x.n as n, case when x.k = 'ip' then {octets} else {fresh} end as s)),
        x -> struct(x.m as m, x.k as k, case x.k when 'card' then {card} when 'iban' then {iban} else x.s end as s)),
        x -> case when x.k = 'email' then {cased} when x.k = 'iban' then {spaced} when x.k = 'ip' then x.s else {numbers} end)[0]"""


# --- names -----------------------------------------------------------------------------------------------------------

_CAPITAL = r"^[\p{Lu}\p{Lt}\p{Lo}]"


def _script(w: str) -> str:
    return f"case when {w} rlike '\\\\p{{IsCyrillic}}' then 'cyrillic' when {w} rlike '\\\\p{{IsGreek}}' then 'greek' else 'latin' end"


def _name_words(m: str) -> str:
    """SQL of ``struct(title, w, s)`` of a mention: words as ``struct(w, core, role, script)``, and what stands between."""
    gender = f"case when x.title rlike '^(?:{_sql(_both_cases(TITLES_F))})(?![\\\\p{{L}}-])' then 'f' when x.title rlike '^(?:{_sql(_both_cases(TITLES_M))})(?![\\\\p{{L}}-])' then 'm' else 'n' end"
    family = "array_max(transform(x.s, (y, i) -> case when i < size(x.w) and y rlike '\\\\s' then i else 0 end))"
    role = f"""case when not w rlike '{_sql(_CAPITAL)}' or (w in ('Mc', 'Mac') and i + 1 < size(x.w) and x.s[i + 1] = '') then 'kept'
        when length(w) = 1 and w rlike '\\\\p{{Lu}}' then 'initial' when i >= x.f then 'family' else concat('given_', x.g) end"""
    rest = "substring(x.m, length(x.title) + 1)"
    return f"""transform(transform(transform(array(struct({m} as m, regexp_extract({m}, '^{_sql(_TITLE)}', 0) as title)),
        x -> struct(x.title as title, regexp_extract_all({rest}, '{_sql(WORDS)}', 0) as w, split({rest}, '{_sql(WORDS)}', -1) as s)),
        x -> struct(x.title as title, x.w as w, x.s as s, {family} as f, {gender} as g)),
        x -> struct(x.title as title, transform(x.w, (w, i) -> struct(w as w, lower(w) as core, {role} as role, {_script("w")} as script)) as w, x.s as s))[0]"""


def _arr(words: str) -> str:
    return "array(" + ", ".join(f"'{x}'" for x in words.split()) + ")"


def _stock_name(role: str, script: str, core: str, salt: str, key: str) -> str:
    """SQL of the surrogate of a word in lower case: two syllables and one more for each salt, and an ending of its role."""
    byte = "cast(conv(substring(h, 1 + 2 * (j % 30), 2), 16, 10) as int)"
    syllables = f"case {script} " + " ".join(f"when '{s}' then {_arr(x['syllables'])}" for s, x in STOCK.items()) + " end"
    endings = f"case concat({script}, ' ', {role}) " + " ".join(f"when '{s} {r}' then {_arr(x[r])}" for s, x in STOCK.items() for r in ("family", "given_m", "given_f", "given_n")) + " end"
    return f"""transform(array(sha2(concat('{_sql(key)}', '|', {role}, '|', {core}, '|', {salt}), 256)), h ->
        concat(array_join(transform(sequence(0, 1 + {salt}), j -> ({syllables})[{byte} % 32]), ''), ({endings})[cast(conv(substring(h, 63, 2), 16, 10) as int) % 8]))[0]"""


def _initial(w: str, key: str) -> str:
    """SQL of another capital for an initial, moved on by a keyed step."""
    abc = f"case {_script(w)} " + " ".join(f"when '{s}' then '{x['initials']}'" for s, x in STOCK.items()) + " end"
    step = f"cast(conv(substring(sha2('{_sql(key)}|initial', 256), 1, 6), 16, 10) as int)"
    return f"transform(array({abc}), abc -> substring(abc, 1 + (locate({w}, abc) + {step} % (length(abc) - 1)) % length(abc), 1))[0]"


def _cased(w: str, s: str) -> str:
    return f"case when length({w}) > 1 and {w} = upper({w}) and {w} <> lower({w}) then upper({s}) else concat(upper(substring({s}, 1, 1)), substring({s}, 2)) end"


def detect(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """``docs`` as struct ``row``, with ``t`` (text, empty for null), ``parts`` between mentions and ``found``: an array of
    ``struct(m, k, n)``: mention, type and normal form."""
    own = docs.select(F.struct("*").alias("row"), text_or_empty(F.col(text_col)).alias("t"))
    any_ = _sql(_ANY)
    hit = F.expr(f"t rlike '{_sql(_HINT)}' and t rlike '{any_}'")
    own = own.withColumn("found", F.when(hit, F.expr(f"regexp_extract_all(t, '{any_}', 0)")))
    own = own.withColumn("parts", F.when(F.size("found") > 0, F.expr(f"split(t, '{any_}', -1)")))
    own = own.withColumn("found", F.expr(f"transform(found, m -> struct(m as m, {_kind('m')} as k))"))
    return own.withColumn("found", F.expr(f"transform(found, x -> struct(x.m as m, x.k as k, {_normal('x.m', 'x.k')} as n))"))


def entities(found: DataFrame) -> DataFrame:
    """Distinct ``k, n`` of the corpus with the number of mentions and one mention as it stands."""
    return found.where("size(found) > 0").select(F.inline("found")).groupBy("k", "n").agg(F.count("*").alias("n_mentions"), F.min("m").alias("m"))


def name_words(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Distinct ``role, script, core`` of the names of a corpus; only texts with a title are looked at."""
    titled = docs.where(text_or_empty(F.col(text_col)).rlike(_TITLE))
    each = detect(titled, text_col).select(F.explode_outer(F.expr(f"transform(filter(found, y -> y.k = 'name'), y -> {_name_words('y.m')}.w)")).alias("w"))
    return each.where("w is not null").select(F.inline("w")).where("role not in ('kept', 'initial')").select("role", "script", "core").distinct()


def clashing_salts(words: DataFrame, key: str, tries: int = 24) -> DataFrame | None:
    """``(role, core, salt)`` of the name words that need another salt than 0 for distinct surrogates; None if there is none.

    Of words with one surrogate the first keeps it; each further salt makes the space of surrogates 32 times as large.
    """
    made = durable(words.select("role", "script", "core", F.lit(0).alias("salt")))
    real = made.select(F.col("core").alias("s")).distinct()
    moved = False
    for _ in range(tries):
        fresh = durable(made.withColumn("s", F.expr(_stock_name("role", "script", "core", "salt", key))))
        owner = fresh.groupBy("s").agg(F.min(F.struct("salt", "role", "core")).alias("o"), F.count("*").alias("c")).where("c > 1").drop("c")
        bad = fresh.join(owner, "s").where("o.core <> core or o.role <> role").select("role", "core")
        bad = durable(bad.union(fresh.join(real, "s", "left_semi").select("role", "core")).distinct().withColumn("b", F.lit(1)))
        if bad.isEmpty():
            return made.where("salt > 0").select("role", "core", "salt") if moved else None
        moved = True
        made = durable(made.join(bad, ["role", "core"], "left").select("role", "script", "core", (F.col("salt") + F.coalesce("b", F.lit(0))).alias("salt")))
    raise RuntimeError(f"surrogates still clash after {tries} salts")


def _rewritten(found: DataFrame, key: str, names: bool) -> DataFrame:
    """Adds ``text`` and ``n`` to detected rows; ``names``: rows may hold names, with ``salts`` of their words."""
    other = _surrogate("y.m", "y.k", "y.n", key)
    join = "array_join(transform(parts, (p, i) -> concat(p, case when i < size(made) then made[i] else '' end)), '')"
    if not names:
        found = found.withColumn("made", F.expr(f"case when size(found) > 0 then transform(found, y -> {other}) end"))
        return found.withColumns({"text": F.expr(f"case when size(found) > 0 then {join} else t end"), "n": F.coalesce(F.size("found"), F.lit(0))})
    salt = "coalesce(try_element_at(salts, concat(z.role, '|', z.core)), 0)"
    found = found.withColumn("named", F.expr(f"transform(found, y -> case when y.k = 'name' then {_name_words('y.m')} end)"))
    # one entry for each word: a family name rather than a given one
    own = "array_sort(array_distinct(flatten(transform(filter(named, y -> y is not null), y -> transform(filter(y.w, z -> z.role not in ('kept', 'initial')), z -> struct(z.core as core, z.role as role, z.script as script))))))"
    found = found.withColumn("words", F.expr(own))
    found = found.withColumn("words", F.expr(f"transform(words, z -> struct(z.core as core, z.role as role, {_stock_name('z.role', 'z.script', 'z.core', salt, key)} as s))"))
    by_role = "coalesce(filter(words, v -> v.core = z.core and v.role = z.role)[0].s, z.core)"
    each = f"case z.role when 'kept' then z.w when 'initial' then {_initial('z.w', key)} else {_cased('z.w', by_role)} end"
    name = f"concat(named[k].title, named[k].s[0], array_join(transform(named[k].w, (z, i) -> concat({each}, named[k].s[i + 1])), ''))"
    found = found.withColumn("made", F.expr(f"transform(found, (y, k) -> case when y.k = 'name' then {name} else {other} end)"))
    # bare mentions: capitalised words between the mentions that are words of names of this text
    w = _sql(WORDS)
    found = found.withColumn("gaps", F.expr(f"transform(parts, p -> struct(regexp_extract_all(p, '{w}', 0) as w, split(p, '{w}', -1) as s))"))
    met = f"array_intersect(array_distinct(flatten(transform(gaps, g -> transform(filter(g.w, x -> length(x) > 1 and x rlike '{_sql(_CAPITAL)}'), x -> lower(x))))), transform(words, z -> z.core))"
    found = found.withColumn("bare", F.expr(met))
    once = "filter(words, (z, i) -> array_contains(bare, z.core) and (i = 0 or words[greatest(i - 1, 0)].core <> z.core))"
    found = found.withColumn("bare", F.expr(f"map_from_entries(transform({once}, z -> struct(z.core, z.s)))"))
    is_bare = f"length(x) > 1 and x rlike '{_sql(_CAPITAL)}' and map_contains_key(bare, lower(x))"
    found = found.withColumn("m", F.expr(f"case when cardinality(bare) > 0 then aggregate(gaps, 0, (a, g) -> a + size(filter(g.w, x -> {is_bare}))) else 0 end"))
    # the capital of O'Brien goes with its name
    led = f"length(x) = 1 and x rlike '\\\\p{{Lu}}' and g.s[i + 1] in ('\\'', '’') and map_contains_key(bare, lower(g.w[i + 1]))"
    word = f"case when {is_bare} then {_cased('x', 'bare[lower(x)]')} when {led} then {_initial('x', key)} else x end"
    gaps = f"transform(gaps, g -> concat(g.s[0], array_join(transform(g.w, (x, i) -> concat({word}, g.s[i + 1])), '')))"
    found = found.withColumn("parts", F.expr(f"case when cardinality(bare) > 0 then {gaps} else parts end"))
    return found.withColumns({"text": F.expr(f"case when size(found) > 0 then {join} else t end"), "n": F.coalesce(F.size("found"), F.lit(0)) + F.coalesce("m", F.lit(0))})


def pseudonymise(docs: DataFrame, key: str, id_col: str = "doc_id", text_col: str = "text", shards: int = 16, broadcast_bytes: int = 32 << 20) -> DataFrame:
    """``docs`` with the same columns and the text rewritten, plus ``n_replaced``.

    A null text stays null and an empty one empty; repeated rows are rewritten alike; an empty table stays empty. Words
    of a titled name are replaced wherever the same text holds them with a capital, be they meant as a name or not.
    Words of scripts without a stock of names get Latin ones. Salts travel by broadcast while their table is within
    ``broadcast_bytes``; beyond it texts with names are joined by their hash, each hash dealt over ``shards``.
    """
    has_name = text_or_empty(F.col(text_col)).rlike(_TITLE)
    words = durable(name_words(docs, text_col))

    def out(found: DataFrame, names: bool) -> DataFrame:
        made = _rewritten(found, key, names)
        kept = [F.when(F.col(f"row.`{text_col}`").isNotNull(), F.col("text")).alias(c) if c == text_col else F.col(f"row.`{c}`").alias(c) for c in docs.columns]
        return made.select(*kept, F.col("n").cast("long").alias("n_replaced"))

    if words.isEmpty():
        return out(detect(docs, text_col), False)
    salts = clashing_salts(words, key)
    named = detect(docs.where(has_name), text_col)
    if salts is None:
        named = named.withColumn("salts", F.lit(None).cast("map<string,int>"))
    else:
        named = named.withColumn("tk", F.struct(F.xxhash64("t"), F.crc32(F.col("t").cast("binary")), F.length("t")))
        named = named.withColumn("shard", F.pmod(F.xxhash64(F.col(f"row.`{id_col}`").cast("string")), F.lit(shards)))
        own = F.expr(f"flatten(transform(filter(found, y -> y.k = 'name'), y -> {_name_words('y.m')}.w))")
        each = named.where("size(found) > 0").select("tk", F.inline(own)).select("tk", "role", "core").distinct()
        per_text = each.join(sized_broadcast(durable(salts), broadcast_bytes), ["role", "core"])
        per_text = per_text.groupBy("tk").agg(F.map_from_entries(F.collect_set(F.struct(F.concat_ws("|", "role", "core"), "salt"))).alias("salts"))
        dealt = per_text.withColumn("shard", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(shards - 1).cast("long"))))
        named = named.join(dealt, ["tk", "shard"], "left")
    return out(named, True).unionByName(out(detect(docs.where(~has_name), text_col), False))
