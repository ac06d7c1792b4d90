"""Personal data replaced by surrogates, in DataFrame operations alone.

Entities (e-mail addresses, IPv4 addresses, card numbers, phone numbers, social security numbers, bank account numbers, titled
names) are found by one regular expression in one pass over whole texts, which cuts each text into plain stretches and entities.
Every entity has a canonical form: addresses in lower case, numbers without separators, a name word by word (given and
family names; titles and particles such as "van" stay). The canonical form gets a surrogate from a keyed SHA-256, and the
surrogate is written in the shape of each mention, so every way of writing an entity has the same surrogate: digits stay
digits, letters stay letters of the same case, separators, the country codes of phones and bank accounts and the first digit of a card
stay, card numbers pass the Luhn test and bank accounts the test modulo 97, names keep gender, script and number of words. "Mr. Smith",
"Mr Smith" and "Mr John Smith" share the family name; a Russian family name in -a after a female title shares it with its male form.

The distinct forms of the corpus are checked: a surrogate that two of them share, or that itself occurs in the
corpus, is drawn again with the next attempt number for all but the first of them, until none clashes.

Names without a title, and names all in capitals, are not found: DataFrame operations have no dictionary of names to tell them by.

Null texts stay null, empty ones empty; texts of any length are taken whole. Repeated rows, equal or null doc_ids keep their rows and get
equal surrogates. An empty table gives an empty result. Only doc_id and text are read, so other columns may have any names. A form that
fills a third of the corpus is one row of the surrogates; its mentions are joined to that row, which AQE may split.
"""
from __future__ import annotations

from pyspark.sql import Column, DataFrame, functions as F

from .common import discard, written

# Titles by gender, particles of names, given names by gender and script, syllables of made-up family names,
# country codes of one and two digits (all others have three).
MALE_TITLES = ["Mr", "Herr", "Monsieur", "Señor", "Sr", "господин"]
FEMALE_TITLES = ["Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "госпожа"]
NEUTRAL_TITLES = ["Dr", "Prof"]
PARTICLES = ["von", "van", "de", "der", "den", "del", "di", "da", "dos", "la", "le", "zu"]
LATIN_MALE = ["Adam", "Bruno", "Carl", "David", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Karl", "Louis", "Martin", "Noel", "Oscar", "Paul"]
LATIN_FEMALE = ["Alice", "Berta", "Clara", "Diana", "Elena", "Flora", "Greta", "Helen", "Irene", "Julia", "Karin", "Laura", "Maria", "Nadia", "Olivia", "Paula"]
CYRILLIC_MALE = ["Антон", "Борис", "Виктор", "Глеб", "Денис", "Егор", "Иван", "Кирилл", "Максим", "Никита", "Олег", "Павел", "Роман", "Семён", "Тимур", "Юрий"]
CYRILLIC_FEMALE = ["Алина", "Вера", "Галина", "Дарья", "Елена", "Жанна", "Зоя", "Ирина", "Ксения", "Лидия", "Мария", "Нина", "Ольга", "Раиса", "Софья", "Юлия"]
LATIN_SYLLABLES = ["ba", "bel", "cor", "da", "den", "fa", "fol", "gar", "hal", "ko", "lam", "lin", "mar", "mo", "nor", "par", "ros", "sal", "ten", "tor", "val", "ver", "win", "zan"]
CYRILLIC_SYLLABLES = ["ба", "бел", "вол", "гор", "да", "дем", "жар", "зай", "ка", "кор", "лан", "мар", "мо", "нов", "ор", "пав", "руд", "сав", "та", "тур", "фед", "хар", "цар", "шув"]
CODES_OF_ONE = ["1", "7"]
CODES_OF_TWO = "20 27 30 31 32 33 34 36 39 40 41 43 44 45 46 47 48 49 51 52 53 54 55 56 57 58 60 61 62 63 64 65 66 81 82 84 86 90 91 92 93 94 95 98".split()

MOST_ROUNDS = 200
DRAW_ROWS = 2000  # forms a task that draws surrogates
_TITLES = "|".join(sorted(MALE_TITLES + FEMALE_TITLES + NEUTRAL_TITLES, key=len, reverse=True))
_SMALL = "|".join(sorted(PARTICLES, key=len, reverse=True))
_W = r"\p{L}\p{N}_"
_WORD = rf"(?!(?:{_TITLES})(?!\p{{L}}))\p{{Lu}}\p{{L}}*+(?:['’-]\p{{Lu}}\p{{L}}*+)*+"
_NAMED = rf"(?:(?:\p{{Lu}}\.|{_SMALL}) ){{0,4}}{_WORD}"
NAME = rf"(?<!\p{{L}})(?:(?:{_TITLES})\.? ){{1,3}}{_NAMED}(?: {_NAMED}){{0,2}}(?!\p{{L}})"
EMAIL = rf"(?<![{_W}.+%-])[A-Za-z0-9._%+-]{{1,64}}+@[A-Za-z0-9-]{{1,63}}(?:\.[A-Za-z0-9-]{{1,63}}){{1,8}}"
OCTET = "(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
IPV4 = rf"(?<![{_W}.]){OCTET}(?:\.{OCTET}){{3}}(?!\.?[{_W}])"
IBAN = rf"(?<![{_W}])[A-Z]{{2}}[0-9]{{2}}(?: ?[A-Z0-9]{{4}}){{2,7}}(?: ?[A-Z0-9]{{1,3}})?(?![{_W}])"
CARD = rf"(?<![{_W}-])[0-9]{{4}}[ -]?[0-9]{{4}}[ -]?[0-9]{{4}}[ -]?[0-9]{{1,7}}(?![{_W}-])"
SSN = rf"(?<![{_W}-])[0-9]{{3}}-[0-9]{{2}}-[0-9]{{4}}(?![{_W}-])"
PHONE = rf"(?<![{_W}+])(?:\+[0-9]{{1,3}}[ .-]?)?(?:\([0-9]{{2,4}}\)[ .-]?|[0-9]{{2,4}}[ .-])[0-9]{{3,4}}[ .-][0-9]{{3,4}}(?![{_W}-])|(?<![{_W}+])\+[0-9]{{8,15}}(?![{_W}])"
ENTITY = "|".join([EMAIL, IPV4, IBAN, CARD, SSN, PHONE, NAME])
HINT = rf"[@0-9]|(?:{_TITLES})\.? "
#: Marks the ends of entities while a text is cut; where a text holds them itself they are written as pairs meanwhile.
CUT, ESCAPE, CUT_AS, ESCAPE_AS = "\x01", "\x02", "\x02\x03", "\x02\x04"
NUMBERS = ["card", "phone", "ssn", "iban"]


def kind_of(v: Column) -> Column:
    whole = lambda p: v.rlike(f"^(?:{p})$")
    return F.when(F.contains(v, F.lit("@")), "email").when(whole(IPV4), "ip").when(whole(IBAN), "iban").when(whole(SSN), "ssn").when(whole(CARD), "card").when(whole(PHONE), "phone").otherwise("name")


def cut_texts(text: Column) -> Column:
    """Plain stretches and entities of a text in turn, beginning and ending with a stretch: one pass of the expression."""
    odd = text.rlike(f"[{CUT}{ESCAPE}]")
    safe = F.when(odd, F.replace(F.replace(text, F.lit(ESCAPE), F.lit(ESCAPE_AS)), F.lit(CUT), F.lit(CUT_AS))).otherwise(text)
    parts = F.split(F.regexp_replace(safe, f"({ENTITY})", f"{CUT}$1{CUT}"), CUT, -1)
    back = lambda p: F.replace(F.replace(p, F.lit(CUT_AS), F.lit(CUT)), F.lit(ESCAPE_AS), F.lit(ESCAPE))
    return F.when(~text.rlike(HINT), F.array(text)).when(odd, F.transform(parts, back)).otherwise(parts)


def units_of(kind: Column, v: Column) -> Column:
    """[(kind, canon, value)] of an entity: itself, or the words of a name, of which titles and particles are kept ("keep")."""
    bare = F.regexp_replace(v, "[^0-9A-Za-z]", "")
    canon = F.when(kind == "email", F.lower(v)).when(kind == "phone", F.concat(F.when(v.startswith("+"), "+").otherwise(""), bare)).when(kind == "iban", F.upper(bare)).when(kind.isin(*NUMBERS), bare).otherwise(v)
    words = F.split(v, " ")
    female, male = (v.rlike(rf"(?<!\p{{L}})(?:{'|'.join(t)})(?!\p{{L}})") for t in (FEMALE_TITLES, MALE_TITLES))
    gender = F.when(female, "f").when(male, "m").otherwise("n")

    def unit(w, i):
        script = F.when(w.rlike(r"^\p{IsCyrillic}"), "c").otherwise("l")
        last = i == F.size(words) - 1
        kept = ~last & (w.rlike(rf"^(?:{_TITLES})\.?$") | w.isin(*PARTICLES))
        base = F.when(female & (script == "c") & w.endswith("а"), F.substring(w, F.lit(1), F.length(w) - 1)).otherwise(w)
        return F.struct(F.when(kept, "keep").when(last, F.concat(F.lit("family_"), script)).otherwise(F.concat_ws("_", F.lit("given"), gender, script)).alias("kind"), F.when(last, base).otherwise(w).alias("canon"), w.alias("value"))

    return F.when(kind == "name", F.transform(words, unit)).otherwise(F.array(F.struct(kind.alias("kind"), canon.alias("canon"), v.alias("value"))))


def _stream(key: str, *parts: Column) -> Column:
    """256 hex digits, 128 bytes, of the keyed hash."""
    return F.concat(*[F.sha2(F.concat_ws("|", F.lit(key), F.lit(str(k)), *parts), 256) for k in range(4)])


def _byte(h: Column, i: Column) -> Column:
    return F.conv(F.substring(h, (F.pmod(i, F.lit(128)) * 2 + 1).cast("int"), F.lit(2)), 16, 10).cast("int")


def _drawn(form: Column, h: Column, skip: Column | None = None) -> Column:
    """`form` with its digits and ASCII letters, from number `skip` on, drawn anew by the byte of their place."""
    first = F.lit(0) if skip is None else skip

    def at(c, i):
        b, code = _byte(h, i), F.ascii(c)
        pick = lambda low, n: F.char((F.lit(low) + b % n).cast("long"))
        return F.when((i < first) | (F.length(c) == 0), c).when(code.between(48, 57), pick(48, 10)).when(code.between(97, 122), pick(97, 26)).when(code.between(65, 90), pick(65, 26)).otherwise(c)

    return F.array_join(F.transform(F.split(form, ""), at), "")


def _luhn(digits: Column) -> Column:
    """`digits` with the last one set so that all pass the Luhn test."""
    body = F.reverse(digits)

    def worth(i):
        d = F.substring(body, i, F.lit(1)).cast("int") * F.when(i % 2 == 0, 2).otherwise(1)
        return F.when(d > 9, d - 9).otherwise(d)

    total = F.aggregate(F.transform(F.sequence(F.lit(2), F.length(body)), worth), F.lit(0), lambda a, x: a + x)
    return F.concat(F.substring(digits, F.lit(1), F.length(digits) - 1), F.pmod(F.lit(10) - total % 10, F.lit(10)).cast("string"))


def _checked_account(form: Column) -> Column:
    """A bank account number with check digits that make it 1 modulo 97, letters counting as 10 to 35."""
    land, rest = F.substring(form, 1, 2), F.substring(form, F.lit(5), F.length(form))
    digits = F.split(F.concat(rest, land, F.lit("00")), "")

    def step(a, c):
        code = F.ascii(c)
        return F.when(F.length(c) == 0, a).when(code >= 65, (a * 100 + code - 55) % 97).otherwise((a * 10 + code - 48) % 97)

    check = F.lit(98) - F.aggregate(digits, F.lit(0), lambda a, c: step(a, c).cast("int"))
    return F.concat(land, F.lpad(check.cast("string"), 2, "0"), rest)


def _pick(names: list[str], b: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, names)), b % len(names) + 1)


def _syllables(cyrillic: Column, h: Column, first: int, count: Column) -> Column:
    part = lambda i: F.when(cyrillic, _pick(CYRILLIC_SYLLABLES, _byte(h, i + first))).otherwise(_pick(LATIN_SYLLABLES, _byte(h, i + first)))
    return F.when(count > 0, F.array_join(F.transform(F.sequence(F.lit(1), F.greatest(count, F.lit(1))), part), "")).otherwise("")


def surrogate(key: str, kind: Column, canon: Column, attempt: Column) -> Column:
    """The surrogate of a canonical form, itself in canonical form. Later attempts have longer names and addresses, so that room is never short."""
    h = _stream(key, kind, canon, attempt.cast("string"))
    more = F.least(F.floor(attempt / 3), F.lit(40)).cast("int")
    cyrillic = kind.endswith("_c")
    name = lambda first: F.initcap(_syllables(cyrillic, h, first, F.lit(3) + more))
    family = F.when(F.contains(canon, F.lit("-")), F.concat(name(0), F.lit("-"), name(50))).otherwise(name(0))
    by_gender = lambda f, m: F.when(kind.startswith("given_f"), _pick(f, _byte(h, F.lit(0)))).when(kind.startswith("given_m"), _pick(m, _byte(h, F.lit(0)))).otherwise(_pick(f + m, _byte(h, F.lit(0))))
    given = F.when(cyrillic, by_gender(CYRILLIC_FEMALE, CYRILLIC_MALE)).otherwise(by_gender(LATIN_FEMALE, LATIN_MALE))
    given = F.when(F.endswith(canon, F.lit(".")), F.concat(F.upper(F.substring(_syllables(cyrillic, h, 1, F.lit(1)), 1, 1)), F.lit("."))).otherwise(F.concat(given, _syllables(cyrillic, h, 1, F.least(attempt, F.lit(40)))))
    domain = F.substring_index(canon, "@", -1)
    top = F.regexp_extract(domain, r"\.[A-Za-z0-9-]+$", 0)
    other_domain = F.concat(_drawn(F.substring(domain, F.lit(1), F.length(domain) - F.length(top)), _stream(key, F.lit("domain"), domain)), top)
    local = F.concat(_drawn(F.substring_index(canon, "@", 1), h), _syllables(F.lit(False), h, 60, more))
    octets = F.concat_ws(".", (_byte(h, F.lit(0)) % 223 + 1).cast("string"), *[(_byte(h, F.lit(k)) % 254 + 1).cast("string") for k in (1, 2, 3)])
    code = F.when(~canon.startswith("+"), 0).when(F.substring(canon, 2, 1).isin(*CODES_OF_ONE), 2).when(F.substring(canon, 2, 2).isin(*CODES_OF_TWO), 3).otherwise(4)
    return (
        F.when(kind == "email", F.concat_ws("@", local, other_domain))
        .when(kind == "ip", octets)
        .when(kind == "card", _luhn(_drawn(canon, h, F.lit(1))))
        .when(kind == "iban", _checked_account(_drawn(canon, h, F.lit(2))))
        .when(kind == "phone", _drawn(canon, h, code))
        .when(kind == "ssn", _drawn(canon, h))
        .when(kind.startswith("family"), family)
        .otherwise(given)
    )


def shaped(kind: Column, value: Column, canon: Column, sur: Column) -> Column:
    """The surrogate in the shape of one mention: its separators, its case, its ending."""
    letters = F.split(value, "")
    digits = F.when(F.startswith(sur, F.lit("+")), F.substring(sur, F.lit(2), F.length(sur))).otherwise(sur)

    def step(a, c):
        fills = c.rlike("[0-9A-Za-z]")
        x = F.substring(digits, a["i"], F.lit(1))
        x = F.when(F.ascii(c).between(97, 122), F.lower(x)).otherwise(x)
        return F.struct(F.concat(a["o"], F.when(fills, x).otherwise(c)).alias("o"), (a["i"] + F.when(fills, 1).otherwise(0)).alias("i"))

    filled = F.aggregate(letters, F.struct(F.lit("").alias("o"), F.lit(1).alias("i")), step, lambda a: a["o"])
    cased = F.array_join(F.transform(F.split(sur, ""), lambda c, i: F.when(F.ascii(F.substring(value, i + 1, F.lit(1))).between(65, 90), F.upper(c)).otherwise(c)), "")
    cased = F.when(F.length(sur) == F.length(value), cased).otherwise(sur)
    ending = F.when(F.length(value) > F.length(canon), F.concat(sur, F.lit("а"))).otherwise(sur)
    return F.when(kind.isin(*NUMBERS), filled).when(kind == "email", cased).when(kind.startswith("family"), ending).otherwise(sur)


def find_entities(cut: DataFrame) -> DataFrame:
    """(row, pos, word, kind, canon, value) of every entity of `cut` (row, parts), names word by word; pos counts from 0 in a text."""
    odd = F.expr("transform(sequence(0, size(parts) div 2 - 1), i -> parts[2 * i + 1])")
    each = cut.where(F.size("parts") > 1).select("row", F.posexplode(odd).alias("pos", "entity")).withColumn("of_", kind_of(F.col("entity")))
    units = each.select("row", "pos", F.posexplode(units_of(F.col("of_"), F.col("entity"))).alias("word", "u_"))
    return units.select("row", "pos", "word", "u_.kind", "u_.canon", "u_.value")


def assign_surrogates(entities: DataFrame, key: str) -> DataFrame:
    """(kind, canon, sur): no two forms of a kind share a surrogate, and none is itself a form of the corpus.

    Each round draws only the forms that still clash; the least form of those that share a surrogate keeps it.
    """
    known = written(entities.where("kind <> 'keep'").groupBy("kind", "canon").agg(F.count("*").alias("n_")), "entities")
    parts = 1 + known.count() // DRAW_ROWS
    still, settled, held = known.select("kind", "canon"), None, [known]
    for attempt in range(MOST_ROUNDS):
        drawn = written(still.repartition(parts, "canon").withColumn("sur", surrogate(key, F.col("kind"), F.col("canon"), F.lit(attempt))), "drawn")
        owner = drawn.groupBy(F.col("kind").alias("ok_"), F.col("sur").alias("os_")).agg(F.min("canon").alias("owner"))
        taken = known.select(F.col("kind").alias("tk_"), F.col("canon").alias("ts_"))
        if settled is not None:
            taken = taken.unionByName(settled.select(F.col("kind").alias("tk_"), F.col("sur").alias("ts_")))
        fine = drawn.join(owner, (F.col("kind") == F.col("ok_")) & (F.col("sur") == F.col("os_")) & (F.col("canon") == F.col("owner")), "left_semi")
        fine = written(fine.join(taken, (F.col("kind") == F.col("tk_")) & (F.col("sur") == F.col("ts_")), "left_anti"), "settled")
        settled = fine if settled is None else settled.unionByName(fine)
        left = drawn.join(fine.select(F.col("kind").alias("fk_"), F.col("canon").alias("fc_")), (F.col("kind") == F.col("fk_")) & (F.col("canon") == F.col("fc_")), "left_anti")
        still = written(left.select("kind", "canon"), "clashes")
        held += [drawn, still]
        if still.isEmpty():
            discard(*held)
            return settled
    raise RuntimeError(f"surrogates still clash after {MOST_ROUNDS} rounds")


def replace_personal_data(docs: DataFrame, key: str) -> DataFrame:
    """doc_id, text (with surrogates), n_entities for every row of `docs` (doc_id, text)."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    cut = slim.select(F.monotonically_increasing_id().alias("row"), "doc_id", F.when(F.col("text").isNotNull(), cut_texts(F.col("text"))).alias("parts"))
    cut = written(cut, "cut")
    entities = written(find_entities(cut.select("row", "parts")), "found")
    chosen = assign_surrogates(entities, key).select(F.col("kind").alias("k_"), F.col("canon").alias("c_"), "sur")
    named = entities.where("kind <> 'keep'").join(chosen, (F.col("kind") == F.col("k_")) & (F.col("canon") == F.col("c_")))
    named = named.select("row", "pos", "word", shaped(F.col("kind"), F.col("value"), F.col("canon"), F.col("sur")).alias("new"))
    kept = entities.where("kind = 'keep'").select("row", "pos", "word", F.col("value").alias("new"))
    words = F.transform(F.sort_array(F.collect_list(F.struct("word", "new"))), lambda x: x["new"])
    per_place = named.unionByName(kept).groupBy("row", "pos").agg(F.array_join(words, " ").alias("new"))
    per_row = per_place.groupBy(F.col("row").alias("row_")).agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "new"))), lambda x: x["new"]).alias("subs"))
    marked = cut.where(F.size("parts") > 1).join(per_row, F.col("row") == F.col("row_"))
    whole = F.expr("array_join(transform(parts, (p, i) -> if(i % 2 = 0, p, subs[i div 2])), '')")
    done = marked.select("doc_id", whole.alias("text"), F.expr("cast(size(parts) div 2 as bigint)").alias("n_entities"))
    plain = cut.where("parts is null or size(parts) = 1").select("doc_id", F.expr("parts[0]").alias("text"), F.lit(0).cast("long").alias("n_entities"))
    return done.unionByName(plain)
