"""Surrogates for personal data, in DataFrame functions only.

Detected entities get keyed replacements of their own type: the same entity gets the same surrogate wherever it
stands (coreference), different entities get different ones (checked over the whole corpus, with further attempts
for those that collide with each other or with an entity that really occurs; attempts that go on draw from wider and
wider forms, so no form is ever used up). Punctuation, script, letter case, check digit and gender are kept, and length
but for names and widened forms.

A person is found by a title. What is replaced are the words of the name, each by itself over the whole corpus: a word
is a given name if it mostly stands before another word of a name, else a family name, and its gender is that of the
titles that tell one. So a person has one surrogate under any title and in any letter case, a family name alone goes
with the full name, and words of a name that was found in a text are replaced in that text without a title too.
"""

from __future__ import annotations

import hashlib
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from eqmat.storage import saved

#: Titles by the gender they tell, and given and family names by script to choose surrogates from.
TITLES = {
    "m": "Mr|Herr|Señor|Monsieur|Sir|[Гг]осподин|[Гг]-н|[Κκ]ύριος|[Κκ]ύριο|[Κκ]ύριε|κ",
    "f": "Mrs|Ms|Miss|Frau|Señora|Madame|Mme|[Гг]оспожа|[Гг]-жа|[Κκ]υρία|[Κκ]α",
    "n": "Dr|Prof|[Дд]октор|[Дд]-р|[Пп]рофессор|[Пп]роф|[Δδ]ρ|[Κκ]αθηγητής|[Κκ]αθηγήτρια",
}
GIVEN = {
    "m": "Adam Bruno Carl David Emil Felix Gustav Hugo Ivan Jonas Karl Leon Martin Nils Oscar Paul Robin Simon Tomas Viktor".split(),
    "f": "Anna Berta Clara Diana Elena Flora Greta Helena Ida Julia Karla Lena Maria Nora Olga Paula Rosa Sara Tina Vera".split(),
    "n": "Alex Chris Dana Eden Finley Gabriel Jamie Kim Lee Morgan Noel Quinn Robin Sam Toni".split(),
}
ONSETS, VOWELS = "B C D F G H K L M N P R S T V W Z Br Dr Gr Kl Pr St Tr".split(), "a e i o u".split()
CYRILLIC_ONSETS, CYRILLIC_VOWELS = "Б В Г Д Ж З К Л М Н П Р С Т Ф Х Ч Ш".split(), "а е и о у".split()
GREEK_ONSETS, GREEK_VOWELS = "Β Γ Δ Ζ Θ Κ Λ Μ Ν Π Ρ Σ Τ Φ Χ".split(), "α ε ι ο υ".split()
CYRILLIC_GIVEN = {"m": "Иван Пётр Олег Борис Павел".split(), "f": "Анна Ольга Вера Нина Мария".split(), "n": "Саша Женя Валя".split()}
GREEK_GIVEN = {"m": "Νίκος Γιάννης Πέτρος Κώστας".split(), "f": "Μαρία Ελένη Άννα Σοφία".split(), "n": "Αλέξης Χάρις".split()}

#: One pattern for all types; in alternatives of one place the first wins.
EMAIL = r"(?<![A-Za-z0-9._%+\-])[A-Za-z0-9._%+\-]++@[A-Za-z0-9\-]+(?:\.[A-Za-z0-9\-]+)+"
IP = r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\d]|\.\d)"
PHONE = r"(?<![\d\w])(?:\+\d{1,3}[ .\-]?)?\(\d{2,4}\)[ .\-]?\d{3,4}[ .\-]?\d{3,4}(?!\d)|(?<![\d\w])\+\d{1,3}(?:[ .\-]?\d{2,4}){2,5}(?!\d)|(?<![\d\w.\-])\d{3}[.\-]\d{3}[.\-]\d{4}(?![\d\w])"
SSN = r"(?<![\d\w\-])\d{3}-\d{2}-\d{4}(?![\d\w\-])"
IBAN = r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])"
CARD = r"(?<![\w.\-])\d(?:[ \-]?\d){12,18}(?![\w\-])"
SECRET = r"(?<![A-Za-z0-9])(?:(?=[a-f]*\d)(?=\d*[a-f])[0-9a-f]{32,128}|(?=[A-F]*\d)(?=\d*[A-F])[0-9A-F]{32,128})(?![A-Za-z0-9])"
#: Tokens in which letter case counts: of three parts (JWT), with a known prefix, long and of mixed case, the body of a
#: private key, and a value with a letter and a digit that is assigned to a name like token, key or password.
TOKEN = "|".join([
    r"(?<![A-Za-z0-9_\-])eyJ[A-Za-z0-9_\-]{8,}+\.[A-Za-z0-9_\-]{8,}+\.[A-Za-z0-9_\-]{8,}+",
    r"(?<![A-Za-z0-9])(?:(?:sk|pk|rk|gh[oprsu]|github_pat|glpat|xox[abeprs]|hf|npm)[_\-](?=[A-Za-z_\-]*\d)[A-Za-z0-9_\-]{16,}+|A[KS]IA[A-Z0-9]{16}(?![A-Za-z0-9])|AIza[A-Za-z0-9_\-]{35})",
    r"(?<![A-Za-z0-9])(?=[A-Za-z]*\d)(?=[a-z0-9]*[A-Z])(?=[A-Z0-9]*[a-z])[A-Za-z0-9]{32,}+={0,2}",
    r"(?<=PRIVATE KEY-----)[A-Za-z0-9+/=\s]{16,}+(?=-----END)",
    r"(?<=[=:\s\"'])(?=[A-Za-z+/_.~!#$%^&*\-]{0,80}\d)(?=[^A-Za-z\s]{0,80}[A-Za-z])(?<=(?i:token|secret|passw(?:or)?d|pwd|key)[\"']?\s{0,2}[=:]\s{0,2}[\"']?)[A-Za-z0-9+/_.~!#$%^&*\-]{8,}+={0,2}",
])
_CAP = r"\p{Lu}[\p{L}'’\-]+"
_TITLE = "(?:" + "|".join([*TITLES.values(), *[w.upper() for t in TITLES.values() for w in t.split("|") if w.isalpha() and len(w) > 1]]) + r")\.? "
#: A title is looked for only where a letter stands that one begins with.
_TITLED = f"(?=[{''.join(sorted({c for t in TITLES.values() for w in t.split('|') for c in (w[1:3] if w[0] == '[' else w[0])}))}])" + r"(?<!\p{L})" + _TITLE
PERSON = rf"{_TITLED}{_CAP}(?: {_CAP}){{0,2}}"
#: What every entity has: a text without any of it needs no closer look.
SIGN = rf"[0-9@]|PRIVATE KEY-----|{_TITLED}\p{{Lu}}"
TYPES = {"email": EMAIL, "secret": SECRET, "ip": IP, "iban": IBAN, "phone": PHONE, "ssn": SSN, "card": CARD, "token": TOKEN, "person": PERSON}
PATTERN = "|".join(f"(?:{p})" for p in TYPES.values())
WIDER_AFTER = 6  # attempts within a form before it grows


def _sql(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def entity_type(e: Column) -> Column:
    """The type whose pattern an entity has by itself; others are words of names, if of letters, or secrets found by what
    stands around them."""
    out = None
    for name, p in TYPES.items():
        hit = F.regexp_like(e, F.lit(f"^(?:{p})$"))
        out = F.when(hit, F.lit(name)) if out is None else out.when(hit, F.lit(name))
    return out.when(F.regexp_like(e, F.lit(r"^[\p{L}'’\-]+$")), F.lit("name")).otherwise(F.lit("other"))


def _normal(kind: Column, e: Column) -> Column:
    """What makes two mentions one entity: numbers by their digits, words and addresses without letter case."""
    digits = F.regexp_replace(e, r"[ .\-()]", "")
    return F.when(kind.isin("phone", "ssn", "card", "iban"), digits).when(kind.isin("email", "secret", "name"), F.lower(e)).otherwise(e)


def _gender(e: Column) -> Column:
    out = F.lit("n")
    for g in ("f", "m"):
        out = F.when(F.regexp_like(e, F.lit(rf"(?i)^(?:{TITLES[g]})(?!\p{{L}})")), F.lit(g)).otherwise(out)
    return out


def _array(words: list[str]) -> str:
    return "array(" + ",".join("'" + w.replace("'", "\\'") + "'" for w in words) + ")"


def _hmac(key: str, message: str) -> str:
    """HMAC-SHA512 of a string column under key, as 128 hexadecimal digits."""
    raw = key.encode()
    raw = (hashlib.sha512(raw).digest() if len(raw) > 128 else raw).ljust(128, b"\0")
    inner, outer = (bytes(c ^ x for c in raw).hex() for x in (0x36, 0x5C))
    return f"sha2(concat(X'{outer}', unhex(sha2(concat(X'{inner}', encode({message}, 'UTF-8')), 512))), 512)"


def _replacement(key: str) -> list[tuple[str, str]]:
    """Columns that make a surrogate ``sur`` from kind, norm, gender and attempt; each may use those before it."""
    digest = _hmac(key, "concat_ws('|', kind, norm, cast(attempt as string))")
    # A hexadecimal digit of the digest at place i, as a number; 128 of them, used around.
    at = "cast(conv(substr(digest, pmod(i * 2, 126) + 1, 2), 16, 10) as int)"
    digit = f"cast(pmod({at}, 10) as string)"
    same_kind = f"case when c rlike '[0-9]' then {digit} when c rlike '[a-z]' then substr('abcdefghijklmnopqrstuvwxyz', pmod({at}, 26) + 1, 1) when c rlike '[A-Z]' then substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ', pmod({at}, 26) + 1, 1) else c end"
    chars = "split(norm, '')"
    each = lambda rule: f"array_join(transform({chars}, (c, i) -> {rule}), '')"
    hexed = "case when c rlike '[0-9a-f]' then substr('0123456789abcdef', pmod(%s, 16) + 1, 1) else c end" % at
    local = "split_part(norm, '@', 1)"
    email = f"concat(array_join(transform(split({local}, ''), (c, i) -> {same_kind}), ''), '@', substr(digest, 90, 10), '.example.com')"
    ip = "concat_ws('.', " + ", ".join(f"cast(pmod(cast(conv(substr(digest, {8 * k + 1}, 6), 16, 10) as bigint), {223 if k == 0 else 254}) + 1 as string)" for k in range(4)) + ")"
    number = each(f"case when i = 0 and c rlike '[1-9]' then cast(pmod({at}, 9) + 1 as string) when c rlike '[0-9]' then {digit} else c end")
    # A national prefix and the three-digit exchange 555 of made-up numbers stay while attempts are few.
    made_up = f"attempt < {WIDER_AFTER} and norm rlike '^\\\\+\\\\d{{1,3}}\\\\d{{3}}555\\\\d{{4}}$'"
    phone = f"case when {made_up} then concat(regexp_extract(norm, '^(\\\\+\\\\d{{1,3}})\\\\d{{3}}555\\\\d{{4}}$', 1), substr(num, length(norm) - 9, 3), '555', substr(num, length(norm) - 3, 4)) when norm like '+%' then concat('+', substr(norm, 2, 1), substr(num, 3)) else num end"
    iban = f"concat(substr(norm, 1, 2), substr({each(same_kind)}, 3))"
    luhn = lambda col, upto: f"aggregate(sequence(1, {upto}), 0, (a, p) -> a + case when pmod({upto} - p, 2) = %d then cast(substr({col}, p, 1) as int) * 2 - case when cast(substr({col}, p, 1) as int) > 4 then 9 else 0 end else cast(substr({col}, p, 1) as int) end)"
    valid = f"pmod({luhn('norm', 'length(norm)') % 1}, 10) = 0"
    checked = f"concat(substr(num, 1, length(num) - 1), cast(pmod(10 - pmod({luhn('num', '(length(num) - 1)') % 0}, 10), 10) as string))"
    card = f"case when {valid} then {checked} else num end"
    pick = lambda words, k: f"element_at({_array(words)}, pmod(cast(conv(substr(digest, {k}, 6), 16, 10) as int), {len(words)}) + 1)"
    syllables = lambda on, vo, first, n: "concat(" + ", ".join(f"{pick(on, 13 * k + 9)}, {pick(vo, 13 * k + 15)}" for k in range(first, first + n)) + ")"
    # A given name of the list first; later ones go on with syllables and an ending of the gender.
    longer = lambda on, vo, ends: f"case when attempt < 2 then '' else concat({syllables(on, vo, 0, 1)}, {pick(on, 61)}, case gender when 'f' then '{ends[0]}' when 'm' then '{ends[1]}' else '{ends[2]}' end) end"
    given = lambda sets: f"case gender when 'm' then {pick(sets['m'], 1)} when 'f' then {pick(sets['f'], 1)} else {pick(sets['n'], 1)} end"
    name = lambda sets, on, vo, ends: f"case when gender = '' then {syllables(on, vo, 0, 4)} else concat({given(sets)}, {longer(on, vo, ends)}) end"
    cyrillic, greek, latin = name(CYRILLIC_GIVEN, CYRILLIC_ONSETS, CYRILLIC_VOWELS, "аое"), name(GREEK_GIVEN, GREEK_ONSETS, GREEK_VOWELS, "αοε"), name(GIVEN, ONSETS, VOWELS, "aoe")
    person = f"lower(concat(case when norm rlike '[\\\\p{{IsCyrillic}}]' then {cyrillic} when norm rlike '[\\\\p{{IsGreek}}]' then {greek} else {latin} end, case when attempt < {WIDER_AFTER} then '' when norm rlike '[\\\\p{{IsCyrillic}}]' then {syllables(CYRILLIC_ONSETS, CYRILLIC_VOWELS, 4, 2)} when norm rlike '[\\\\p{{IsGreek}}]' then {syllables(GREEK_ONSETS, GREEK_VOWELS, 4, 2)} else {syllables(ONSETS, VOWELS, 4, 2)} end))"
    whole = f"case kind when 'email' then {email} when 'secret' then {each(hexed)} when 'ip' then {ip} when 'iban' then {iban} when 'phone' then {phone} when 'card' then {card} when 'ssn' then num when 'name' then {person} else {each(same_kind)} end"
    # Later attempts append digits (letters to a name), one more each time, so that there is always a free value.
    extra = f"greatest(0, attempt - {WIDER_AFTER} + 1)"
    more = f"case when {extra} = 0 or kind = 'ip' and attempt < {3 * WIDER_AFTER} then '' when kind = 'name' then translate(substr(digest, 100, {extra} - 1), '0123456789', 'ghijklmnop') else array_join(transform(sequence(1, {extra}), i -> {digit}), '') end"
    return [("digest", digest), ("num", number), ("sur", f"concat({whole}, {more})")]


def surrogate_table(entities: DataFrame, key: str) -> DataFrame:
    """kind, norm -> sur for distinct entities(kind, norm, gender), no two of them alike.

    Each attempt draws surrogates for those that have none yet. A draw is taken if no other entity has it, neither as
    its surrogate nor as itself; of several that draw alike the least entity takes it. Attempts beyond WIDER_AFTER draw
    longer values, so all entities get one however many there are.
    """
    left = entities.withColumn("attempt", F.lit(0))
    real = entities.select("kind", F.col("norm").alias("sur")).distinct()
    done = None
    for attempt in count():
        drawn = left
        for column, rule in _replacement(key):
            drawn = drawn.withColumn(column, F.expr(rule))
        firsts = drawn.groupBy("kind", "sur").agg(F.min("norm").alias("norm"))
        free = firsts.join(real, ["kind", "sur"], "left_anti")
        if done is not None:
            free = free.join(done.select("kind", "sur"), ["kind", "sur"], "left_anti")
        taken = free.select("kind", "norm", "sur")
        done = saved(taken if done is None else done.unionByName(taken), "surrogates")
        left = saved(entities.join(done, ["kind", "norm"], "left_anti"), "collided")
        if left.isEmpty():
            return done
        left = left.withColumn("attempt", F.lit(attempt + 1))


def _dressed(form: Column, kind: Column, sur: Column) -> Column:
    """The surrogate in the form of the mention: its separators and letter case; what a widened one has more comes last."""
    spaced = F.expr(
        "concat(array_join(transform(split(form, ''), (c, i) -> case when c rlike '[ .()\\\\-]' then c"
        " else substr(sur, length(regexp_replace(substr(form, 1, i + 1), '[ .()\\\\-]', '')), 1) end), ''),"
        " substr(sur, length(regexp_replace(form, '[ .()\\\\-]', '')) + 1))"
    )
    upper = (F.upper(form) == form) & F.regexp_like(form, F.lit(r"\p{Lu}")) & (F.length(form) > 1)
    return F.when(kind.isin("phone", "ssn", "card", "iban") & (F.length(form) > 0), spaced).when(upper, F.upper(sur)).when(kind == "name", F.initcap(sur)).otherwise(sur)


def _words(mentions: DataFrame) -> DataFrame:
    """_k, i, form, kind -> one row for each word j of a name and one for each other entity, with its norm, the gender
    and place (given or not) that a titled mention tells, and the title in front."""
    titled = F.col("kind") == "person"
    rows = mentions.select("_k", "i", "form", "kind", F.when(titled, F.regexp_extract("form", f"^{_TITLE}", 0)).otherwise("").alias("title"))
    parts = F.when(titled, F.split(F.expr("substr(form, length(title) + 1)"), " ")).otherwise(F.array("form"))
    rows = rows.select("_k", "i", "title", "kind", F.size(parts).alias("n"), F.posexplode(parts).alias("j", "form"))
    told = F.when(titled, F.when(F.col("j") < F.col("n") - 1, _gender(F.col("title"))).otherwise(""))
    rows = rows.withColumn("told", told).withColumn("kind", F.when(titled, "name").otherwise(F.col("kind")))
    return rows.select("_k", "i", "j", F.when(F.col("j") == 0, F.col("title")).otherwise(" ").alias("ahead"), "form", "kind", _normal(F.col("kind"), F.col("form")).alias("norm"), "told")


def entities_of(words: DataFrame) -> DataFrame:
    """kind, norm, gender of distinct entities; of a name: m, f or n for a given name by the titles that tell most, empty
    for a family name (also where as many mentions say the one as the other)."""
    times = lambda g: F.sum(F.when(F.col("told") == g, 1).otherwise(0))
    counted = words.groupBy("kind", "norm").agg(times("m").alias("m"), times("f").alias("f"), times("n").alias("n"), times("").alias("last"))
    given = F.when(F.col("m") > F.col("f"), "m").when(F.col("f") > F.col("m"), "f").otherwise("n")
    return counted.select("kind", "norm", F.when(F.col("m") + F.col("f") + F.col("n") > F.col("last"), given).otherwise("").alias("gender"))


def _found(text: str = "text") -> Column:
    """The mentions of a text in order. Where a name is found by its title, its words count anywhere in the text."""
    people = f"filter(_e, x -> x rlike {_sql('^(?:' + PERSON + ')$')})"
    words = f"array_distinct(flatten(transform({people}, x -> split(regexp_replace(x, {_sql('^' + _TITLE)}, ''), ' '))))"
    forms = f"array_distinct(flatten(transform({words}, x -> array(x, upper(x), initcap(x)))))"
    return F.expr(f"concat({_sql(PATTERN + '|(?<!' + chr(92) + 'p{L})(?:')}, array_join({forms}, '|'), {_sql(')(?!' + chr(92) + 'p{L})')})")


def replace_personal(docs: DataFrame, key: str) -> DataFrame:
    """docs with the entities in text replaced and all other columns and rows as they are.

    Null and empty texts stay; repeated rows get the same replacements; an empty table stays empty. Texts without an
    entity are not moved. The key decides the surrogates, as that of an HMAC: keep it secret, it must not be empty, and
    change it to break the link.
    """
    if not key:
        raise ValueError("a secret key is needed")
    names = docs.columns
    signed = F.coalesce(F.expr(f"text rlike {_sql(SIGN)}"), F.lit(False))
    found = docs.where(signed).withColumn("_e", F.expr(f"regexp_extract_all(text, {_sql(PATTERN)}, 0)"))
    named = F.exists("_e", lambda x: F.regexp_like(x, F.lit(f"^(?:{PERSON})$")))
    found = found.withColumn("_p", F.when(named, _found()))
    found = saved(found.withColumn("_e", F.when(F.col("_p").isNull(), F.col("_e")).otherwise(F.expr("regexp_extract_all(text, _p, 0)"))), "signed")
    some = F.size("_e") > 0
    # One row for each list of mentions: copies of a text share it.
    lists = saved(found.where(some).select("_e").distinct().withColumn("_k", F.sha2(F.array_join("_e", "\x1f"), 256)), "mentions")
    mentions = lists.select("_k", F.posexplode("_e").alias("i", "form")).withColumn("kind", entity_type(F.col("form")))
    words = saved(_words(mentions), "mentions")
    table = surrogate_table(saved(entities_of(words), "entities"), key)
    dressed = words.join(table, ["kind", "norm"]).select("_k", "i", "j", F.concat("ahead", _dressed(F.col("form"), F.col("kind"), F.col("sur"))).alias("new"))
    dressed = dressed.groupBy("_k", "i").agg(F.array_join(F.sort_array(F.collect_list(F.struct("j", "new")))["new"], "").alias("new"))  # at most three words
    of = dressed.groupBy("_k").agg(F.sort_array(F.collect_list(F.struct("i", "new"))).alias("_n"))  # a text's own mentions
    of = of.select(F.col("_k").alias("_key"), F.col("_n.new").alias("_new"))
    hit = found.where(some).withColumn("_k", F.sha2(F.array_join("_e", "\x1f"), 256)).drop("_e")
    hit = hit.join(of, F.col("_k") == F.col("_key"))
    gaps = F.when(F.col("_p").isNull(), F.expr(f"split(text, {_sql(PATTERN)}, -1)")).otherwise(F.expr("split(text, _p, -1)"))
    text = F.array_join(F.zip_with(gaps, F.concat(F.col("_new"), F.array(F.lit(""))), lambda gap, new: F.concat(gap, new)), "")
    changed = hit.withColumn("text", text)
    if "n_chars" in names:
        changed = changed.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return changed.select(*names).unionByName(found.where(~some).select(*names)).unionByName(docs.where(~signed))


def count_entities(docs: DataFrame) -> DataFrame:
    """doc_id, kind, n: what would be replaced."""
    e = docs.select("doc_id", F.explode(F.expr(f"regexp_extract_all(text, {_sql(PATTERN)}, 0)")).alias("form"))
    return e.select("doc_id", entity_type(F.col("form")).alias("kind")).groupBy("doc_id", "kind").agg(F.count("*").alias("n"))
