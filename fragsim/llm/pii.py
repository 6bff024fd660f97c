"""Replacement of personal data by keyed surrogates.

Entities are found by one pattern, in one pass that sets marks around them: e-mail addresses, IPv4 and IPv6
addresses, card numbers, telephone numbers, national numbers, IBANs, access keys and tokens, and names after a
form of address; the words of such names are then found without one too, in the same document.  Each entity is
reduced to *units* (a type and a canonical form: digits of a number, lower-case address, each word of a name);
the surrogate of a unit is an HMAC-SHA-256 function of type and canonical form under the caller's key, so all
mentions of one unit, in whatever format and after whatever title, get the same surrogate.  Format is kept:
separators, case, country code, the first digit and check digit of cards, octets of addresses, the ending of
domains, the script of letters.  A given name is male or female by the forms of address that most of its mentions
in the corpus follow, and ends accordingly.

Distinctness is checked over the whole corpus: units whose surrogates meet, or meet a unit that occurs,
draw again with the next attempt number until all differ.  The genders of given names and the few units with an
attempt above zero are the only state beside the key; documents fetch those of their own units.  Every step
is a DataFrame operator.

Defined results: a null text stays null, a text without entities stays as it is; repeated rows are
replaced each; an empty table gives an empty result; other columns are ignored by the query form and
kept by ``keep_columns``, whatever their names (n_entities and kinds are replaced).
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import HOT_ROWS, join_on, persist, spread_join, unused

# Forms of address (English, German, French, Spanish, Russian, Greek).
MALE = ("Mr", "Herr", "Herrn", "Monsieur", "Señor", "Sr", "Don", "Sir", "Господин", "Κύριος")
FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Mlle", "Señora", "Señorita", "Sra", "Doña", "Lady", "Госпожа", "Κυρία")
NEUTRAL = ("Dr", "Prof")
_ADDRESS = "|".join(sorted(MALE + FEMALE + NEUTRAL, key=len, reverse=True))

_PARTICLES = ("von", "van", "de", "del", "der", "den", "da", "di", "la", "le", "al", "bin", "zu")
_NAME = r"\p{Lu}[\p{L}\p{M}]*(?:['’]\p{L}[\p{L}\p{M}]*)*"
_PART = f"(?:(?:{'|'.join(_PARTICLES)}) )"
_HEX = "[0-9A-Fa-f]{1,4}"

PATTERNS = {
    "email": r"(?<![._%+-])[\p{L}\p{N}](?:[\p{L}\p{N}._%+-]{0,62}[\p{L}\p{N}])?@(?:[\p{L}\p{N}-]{1,63}\.){1,8}\p{L}{2,24}(?![\p{L}\p{N}])",
    "name": rf"(?:{_ADDRESS})\.? {_PART}{{0,2}}{_NAME}(?:[ -]{_PART}{{0,2}}{_NAME}){{0,2}}",
    "key": r"AKIA[0-9A-Z]{16}(?![A-Za-z0-9])",
    "token": r"(?=[0-9a-f]*[0-9])(?=[0-9a-f]*[a-f])[0-9a-f]{32,64}(?![A-Za-z0-9])",
    "iban": r"[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "ip": r"(?<!\.)(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]{1,2})\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]{1,2})(?![0-9]|\.[0-9])",
    "ipv6": rf"(?<!:)(?:(?:{_HEX}:){{7}}{_HEX}|(?:{_HEX}:){{1,6}}(?::{_HEX}){{1,6}}|::(?:{_HEX}:){{0,6}}{_HEX})(?![:\p{{L}}\p{{N}}])",
    "ssn": r"(?<!-)[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "card": r"[0-9](?:[ -]?[0-9]){12,18}(?![0-9])",
    "phone": r"(?:(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,5}\)|[0-9]{3})[ .-]?[0-9]{3,4}[ .-][0-9]{3,4}(?![0-9])|\+[0-9]{1,3}(?:[ .-]?[0-9]){7,12}(?![0-9]))",
}
# Entities start where no letter or digit stands before; tested first, this spares most positions all else.
_EDGE = r"(?<![\p{L}\p{N}])"
PATTERN = f"{_EDGE}(?:{'|'.join(PATTERNS.values())})"
#: Control characters around entities; the first is doubled by the second where the text itself has it.
_ESCAPE, _MARK = "\x01\x02", "\x01\x03"

# Syllables from which surrogate names are made, by script.
SYLLABLES = {
    "latin": "ba be bo da de do fa fe ga go ha ka ke ko la le lo ma me mi mo na ne no pa pe ra re ro sa se ta".split(),
    "cyrillic": "ба бе бо да де до фа фе га го ха ка ке ко ла ле ло ма ме ми мо на не но па пе ра ре ро са се та".split(),
    "greek": "βα βε βο δα δε δο φα φε γα γο χα κα κε κο λα λε λο μα με μι μο να νε νο πα πε ρα ρε ρο σα σε τα".split(),
}
ENDINGS = {"latin": ("n", "na", "rt"), "cyrillic": ("н", "на", "рт"), "greek": ("ν", "να", "ρτ")}


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _type_sql(e: str) -> str:
    """Type of an entity, first pattern that it matches whole; ``bare`` is a name without form of address."""
    return "CASE " + " ".join(f"WHEN {e} RLIKE {_quoted(f'^(?:{p})$')} THEN '{k}'" for k, p in PATTERNS.items()) + " ELSE 'bare' END"


def _words_sql(e: str) -> str:
    return f"split(regexp_replace({e}, {_quoted(f'^(?:{_ADDRESS})[.]? ')}, ''), '[ -]')"


def _units_sql(e: str) -> str:
    """Units of an entity: array of (kind, canon, said), the last the gender that a form of address gives."""
    digits, words = f"regexp_replace({e}, '[^0-9]', '')", _words_sql(e)
    title = f"regexp_replace({e}, '[.]? .*$', '')"
    gender = f"CASE WHEN i = size({words}) - 1 THEN '' WHEN {title} IN ({', '.join(map(_quoted, FEMALE))}) THEN 'f' WHEN {title} IN ({', '.join(map(_quoted, MALE))}) THEN 'm' ELSE '' END"
    particle = f"w IN ({', '.join(map(_quoted, _PARTICLES))})"
    name = f"transform({words}, (w, i) -> struct(CASE WHEN {particle} THEN 'particle' ELSE 'name' END AS kind, lower(w) AS canon, CASE WHEN {particle} THEN '' ELSE {gender} END AS said))"
    single = f"""transform(array({_type_sql(e)}), t -> struct(t AS kind, CASE t WHEN 'email' THEN lower({e}) WHEN 'phone' THEN right({digits}, 10)
        WHEN 'card' THEN {digits} WHEN 'ssn' THEN {digits} WHEN 'iban' THEN replace({e}, ' ', '') WHEN 'ipv6' THEN lower({e}) ELSE {e} END AS canon, '' AS said))"""
    return f"CASE WHEN {_type_sql(e)} IN ('name', 'bare') THEN {name} ELSE {single} END"


def _byte(stream: str, i: str) -> str:
    return f"cast(conv(substr({stream}, 2 * pmod({i}, 64) + 1, 2), 16, 10) AS int)"


def _letters_sql(text: str, stream: str) -> str:
    """Letters and digits of ``text`` replaced one by one, same case, script and kind."""
    r = _byte(stream, "i")
    return f"""array_join(transform(split({text}, ''), (c, i) -> CASE WHEN c RLIKE '^[0-9]$' THEN cast({r} % 10 AS string)
        WHEN c RLIKE '^[a-z]$' THEN char(97 + {r} % 26) WHEN c RLIKE '^[A-Z]$' THEN char(65 + {r} % 26) ELSE c END), '')"""


def _luhn_sql(digits: str, n: str) -> str:
    """Luhn sum of a digit string whose last place counts once."""
    d = f"cast(substr({digits}, i + 1, 1) AS int)"
    return f"aggregate(sequence(0, {n} - 1), 0, (s, i) -> s + CASE WHEN pmod({n} - 1 - i, 2) = 0 THEN {d} WHEN {d} > 4 THEN 2 * {d} - 9 ELSE 2 * {d} END)"


def _hmac_sql(message: str, key: bytes) -> str:
    """HMAC-SHA-256 as hex digits."""
    block = (hashlib.sha256(key).digest() if len(key) > 64 else key).ljust(64, b"\0")
    inner, outer = (bytes(x ^ pad for x in block).hex() for pad in (0x36, 0x5C))
    return f"sha2(concat(X'{outer}', unhex(sha2(concat(X'{inner}', cast({message} AS binary)), 256))), 256)"


def _surrogate_sql(kind: str, canon: str, attempt: str, key: bytes) -> str:
    """Canonical surrogate of a unit."""
    seed = f"concat_ws('|', substring_index({kind}, '-', 1), cast({attempt} AS string), {canon})"
    stream = f"concat({_hmac_sql(seed, key)}, {_hmac_sql(f'concat({seed}, {_quoted("+")})', key)})"
    digit = lambda n, first: f"array_join(transform(sequence(0, {n} - 1), i -> CASE WHEN i = 0 THEN cast({first} AS string) ELSE cast({_byte(stream, 'i')} % 10 AS string) END), '')"
    size = f"length({canon})"
    body = f"substr({digit(size, f'substr({canon}, 1, 1)')}, 1, {size} - 1)"
    check = f"cast(pmod(10 - pmod({_luhn_sql(f'concat({body}, {_quoted("0")})', size)}, 10), 10) AS string)"
    card = f"CASE WHEN pmod({_luhn_sql(canon, size)}, 10) = 0 THEN concat({body}, {check}) ELSE {digit(size, f'substr({canon}, 1, 1)')} END"
    octets = ", ".join(f"cast({_byte(stream, str(j))} % 254 + 1 AS string)" for j in range(4))
    local, domain, ending = f"split({canon}, '@')[0]", f"regexp_replace(split({canon}, '@')[1], '[.][^.]*$', '')", f"regexp_extract({canon}, '[.][^.]*$', 0)"
    email = f"concat({_letters_sql(local, stream)}, '@', {_letters_sql(domain, _hmac_sql(f'concat({domain}, cast({attempt} AS string))', key))}, {ending})"
    script = lambda w: f"CASE WHEN {w} RLIKE '\\\\p{{IsCyrillic}}' THEN 'cyrillic' WHEN {w} RLIKE '\\\\p{{IsGreek}}' THEN 'greek' ELSE 'latin' END"
    names = []
    for s, parts in SYLLABLES.items():
        pool = "array(" + ", ".join(map(_quoted, parts)) + ")"
        male, female, neutral = map(_quoted, ENDINGS[s])
        end = f"CASE {kind} WHEN 'name-m' THEN {male} WHEN 'name-f' THEN {female} ELSE {neutral} END"
        names.append(f"WHEN '{s}' THEN concat(array_join(transform(sequence(0, 2 + {attempt}), i -> element_at({pool}, {_byte(stream, 'i')} % {len(parts)} + 1)), ''), {end})")
    name = f"CASE {script(canon)} {' '.join(names)} END"
    token = f"array_join(transform(sequence(0, {size} - 1), i -> substr('0123456789abcdef', {_byte(stream, 'i')} % 16 + 1, 1)), '')"
    access = f"concat('AKIA', {_letters_sql(f'substr({canon}, 5)', stream)})"
    iban = f"concat(substr({canon}, 1, 2), {_letters_sql(f'substr({canon}, 3)', stream)})"
    groups = ", ".join(f"substr({stream}, {4 * j + 1}, 4)" for j in range(6))
    return f"""CASE {kind} WHEN 'particle' THEN {canon} WHEN 'ipv6' THEN concat_ws(':', '2001', 'db8', {groups}) WHEN 'email' THEN {email} WHEN 'ip' THEN concat_ws('.', {octets}) WHEN 'card' THEN {card} WHEN 'token' THEN {token}
        WHEN 'key' THEN {access} WHEN 'iban' THEN {iban} WHEN 'phone' THEN {digit(size, f'{_byte(stream, "0")} % 8 + 2')} WHEN 'ssn' THEN {digit(size, f'{_byte(stream, "0")} % 8 + 1')} ELSE {name} END"""


def _overlay_sql(e: str, new: str, which: str) -> str:
    """``new`` laid over the characters of ``e`` of class ``which``, the rest of ``e`` kept."""
    return f"""aggregate(split({e}, ''), named_struct('o', '', 'k', 0), (a, c) -> CASE WHEN c RLIKE '^{which}$'
        THEN named_struct('o', concat(a.o, substr({new}, a.k + 1, 1)), 'k', a.k + 1) ELSE named_struct('o', concat(a.o, c), 'k', a.k) END, a -> a.o)"""


def _render_sql(e: str, units: str, news: str) -> str:
    """The entity with its units' surrogates in its own format."""
    kind, new = f"{units}[0].kind", f"{news}[0]"
    digits = f"regexp_replace({e}, '[^0-9]', '')"
    whole = f"concat(substr({digits}, 1, length({digits}) - length({new})), {new})"
    words = _words_sql(e)
    cased = f"transform({news}, (n, j) -> CASE WHEN {units}[j].kind = 'particle' THEN n WHEN length({words}[j]) > 1 AND {words}[j] = upper({words}[j]) THEN upper(n) ELSE initcap(n) END)"
    title = _quoted(f"^(?:{_ADDRESS})[.]? ")
    between = f"regexp_extract_all(regexp_replace({e}, {title}, ''), '[ -]', 0)"
    name = f"concat(regexp_extract({e}, {title}, 0), array_join(transform({cased}, (n, j) -> concat(CASE WHEN j = 0 THEN '' ELSE {between}[j - 1] END, n)), ''))"
    return f"""CASE WHEN {kind} IN ('phone', 'card', 'ssn') THEN {_overlay_sql(e, whole, '[0-9]')} WHEN {kind} = 'iban' THEN {_overlay_sql(e, new, '[A-Z0-9]')}
        WHEN {kind} IN ('name', 'particle') THEN {name} ELSE {new} END"""


def _marked(text: Column) -> Column:
    """The text with marks around its entities."""
    escaped = F.replace(text, F.lit(_ESCAPE[0]), F.lit(_ESCAPE))
    set_marks = lambda pattern: F.regexp_replace(escaped, pattern, F.lit(f"{_MARK}$0{_MARK}"))
    return set_marks(F.lit(PATTERN))


def find_entities(docs: DataFrame, text_col: str, marked: str) -> DataFrame:
    """Adds ``marked``: the text with marks around entities, names without form of address included."""
    rows = docs.withColumn(marked, _marked(F.col(text_col)))
    title = f"^(?:{_ADDRESS})[.]? "
    named = F.filter(F.split(F.col(marked), _MARK), lambda p, i: (i % 2 == 1) & p.rlike(title))
    of_name = lambda e: F.filter(F.split(F.regexp_replace(e, title, ""), "[ -]"), lambda w: (F.length(w) > 2) & w.rlike(r"^\p{Lu}"))
    (held,) = unused(rows.columns, "_words")
    rows = rows.withColumn(held, F.array_distinct(F.flatten(F.transform(named, of_name))))
    word = F.concat(F.lit("(?:\\Q"), F.array_join(held, "\\E|\\Q"), F.lit("\\E)"))
    bare = F.concat(F.lit(f"{PATTERN}|{_EDGE}"), word, F.lit("(?:[ -]"), word, F.lit(")*(?![\\p{L}\\p{N}])"))
    escaped = F.replace(F.col(text_col), F.lit(_ESCAPE[0]), F.lit(_ESCAPE))
    again = F.regexp_replace(escaped, bare, F.lit(f"{_MARK}$0{_MARK}"))
    return rows.withColumn(marked, F.when(F.coalesce(F.size(held), F.lit(0)) > 0, again).otherwise(F.col(marked))).drop(held)


def unit_table(found: DataFrame, units: str) -> DataFrame:
    """kind, canon, n of the different units; names are name-f, name-m or name-n by most of what is said of them."""
    said = found.select(F.explode(F.flatten(units)).alias("u")).select("u.*").where("kind <> 'particle'")
    counted = said.groupBy("kind", "canon").agg(F.sum(F.expr("CASE said WHEN 'f' THEN 1 WHEN 'm' THEN -1 ELSE 0 END")).alias("lean"), F.count("*").alias("n"))
    gender = F.expr("CASE WHEN kind <> 'name' THEN kind WHEN lean > 0 THEN 'name-f' WHEN lean < 0 THEN 'name-m' ELSE 'name-n' END")
    return counted.select(gender.alias("kind"), "canon", "n")


def resolve_collisions(units: DataFrame, key: bytes, max_rounds: int = 20) -> DataFrame:
    """kind, canon, n, attempt of the units (distinct by kind and canon), raised until all surrogates differ."""
    family = F.substring_index("kind", "-", 1)
    drawn = lambda df: df.withColumn("new", F.expr(_surrogate_sql("kind", "canon", "attempt", key)))
    current = persist(drawn(units.withColumns({"attempt": F.lit(0), "family": family})), "units")
    for _ in range(max_rounds):
        # Among units with one surrogate, the one with the fewest attempts and smallest form keeps it.
        groups = current.groupBy("family", "new").agg(F.min(F.struct("attempt", "canon")).alias("owner"), F.count("*").alias("m")).where("m > 1").drop("m")
        taken = current.join(groups, ["family", "new"]).where("attempt <> owner.attempt or canon <> owner.canon").select("kind", "canon")
        real = current.select("family", F.col("canon").alias("new"))
        onto_real = current.join(real, ["family", "new"], "left_semi").select("kind", "canon")
        clash = persist(taken.unionByName(onto_real).distinct(), "clash")
        if clash.isEmpty():
            return current.drop("new", "family")
        moved = drawn(current.join(clash, ["kind", "canon"], "left_semi").withColumn("attempt", F.col("attempt") + 1).drop("new"))
        current = persist(current.join(clash, ["kind", "canon"], "left_anti").unionByName(moved.select(*current.columns)), "units")
    raise RuntimeError(f"surrogates still collide after {max_rounds} rounds")


def replace_pii(docs: DataFrame, key: bytes, id_col: str = "doc_id", text_col: str = "text", keep_columns: bool = False) -> DataFrame:
    """doc_id, text with surrogates, n_entities, kinds (sorted, distinct); with ``keep_columns`` all columns.

    Whoever has ``key`` can test guesses of what stood in a text; keep it secret and do not store it with the result.
    """
    keep = [c for c in docs.columns if c.lower() not in ("n_entities", "kinds")] if keep_columns else [id_col, text_col]
    marked, units, found, notes, id_, mark = unused([*keep, "n_entities", "kinds"], "_marked", "_units", "_found", "_notes", "_id", "_mark")
    rows = persist(find_entities(docs.select(*keep), text_col, marked), "marked")
    rows = rows.withColumn(found, F.filter(F.split(F.col(marked), _MARK), lambda p, i: i % 2 == 1))
    rows = rows.withColumn(units, F.expr(f"transform(`{found}`, e -> {_units_sql('e')})"))
    rows = rows.withColumns({id_: F.col(id_col), mark: F.xxhash64(text_col)})
    some = rows.where(F.size(found) > 0)
    drawn = resolve_collisions(unit_table(some, units), key)
    noted = persist(drawn.where("attempt > 0 or kind like 'name-%'").select(F.substring_index("kind", "-", 1).alias("kind"), "canon", F.col("kind").alias("full"), "attempt", "n"), "noted")
    # Documents fetch what is noted of their units.
    of_doc = some.select(F.col(id_).alias("i"), F.col(mark).alias("x"), F.explode(F.flatten(units)).alias("u")).select("i", "x", "u.kind", "u.canon").distinct()
    hot = noted.where(F.col("n") > HOT_ROWS).select("kind", "canon")
    met = spread_join(of_doc, noted.drop("n"), ["kind", "canon"], hot)
    entry = F.struct(F.concat_ws("|", "kind", "canon"), F.struct("full", "attempt"))
    met = persist(met.groupBy("i", "x").agg(F.map_from_entries(F.collect_list(entry)).alias(notes)).withColumnsRenamed({"i": id_, "x": mark}), "notes")
    plain = rows.where(F.coalesce(F.size(found), F.lit(0)) <= 0).select(*keep, F.lit(0).cast("long").alias("n_entities"), F.lit("").alias("kinds"))
    some = join_on(some, met, [id_, mark], "left")
    note = f"element_at(`{notes}`, concat_ws('|', u.kind, u.canon))"
    news = f"transform(`{units}`[i], u -> {_surrogate_sql(f'coalesce({note}.full, u.kind)', 'u.canon', f'coalesce({note}.attempt, 0)', key)})"
    (new,) = unused(some.columns, "_new")
    some = some.withColumn(new, F.expr(f"transform(`{found}`, (e, i) -> {news})"))
    shown = F.expr(f"transform(`{found}`, (e, i) -> {_render_sql('e', f'`{units}`[i]', f'`{new}`[i]')})")
    pieces = F.filter(F.split(F.col(marked), _MARK, -1), lambda p, i: i % 2 == 0)
    rebuilt = F.replace(F.array_join(F.zip_with(pieces, shown, lambda p, s: F.concat(p, F.coalesce(s, F.lit("")))), ""), F.lit(_ESCAPE), F.lit(_ESCAPE[0]))
    kinds = F.array_join(F.array_sort(F.array_distinct(F.filter(F.transform(F.flatten(units), lambda u: u["kind"]), lambda k: k != "particle"))), ",")
    out = some.select(*(rebuilt.alias(c) if c == text_col else F.col(c) for c in keep), F.size(found).cast("long").alias("n_entities"), kinds.alias("kinds"))
    return plain.unionByName(out)
