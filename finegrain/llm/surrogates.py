"""Personal data: detected entities get keyed surrogates of the same type, gender, script and format.

Detection is one pattern per type; card numbers must have an issuer's prefix and a valid check digit as well. Persons are found by a
title, by a known given name before a family name, by words that introduce a name ("my name is", "Dear ...,") and before a mail address in
brackets. An entity is its type and canonical value (lower-case address, bare digits, name part), so every mention of it, in
whatever format, gets the same surrogate everywhere. A given name has the gender that its mentions agree on, by the name itself or its
title; where they say nothing or disagree, it gets a name of either gender.

The surrogate is drawn from a keyed hash of type, value and attempt. Three checks follow over all entities of the table: no surrogate
may be a real value of the same type, none may contain the value that it stands for, and no two entities may share one; those that
fail draw again, from a space that grows with every attempt. Entities that still fail after ``MOST_DRAWS`` are an error: no original is ever
written out. So distinct people stay distinct and mentions stay together. Surrogates are then written in the mention's own
format: its separators, its letter case, its check digit, its title.

Everything is DataFrame functions. Only entities shuffle, and of the texts only those that hold one.

Defined results: null stays null and empty stays empty. Texts without an entity pass unchanged. Rows that agree in id and text
share their result. Extra columns pass through under any names; ``n_entities`` and ``entity_kinds`` replace input columns of these names.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from finegrain.llm.filters import split_by_keys
from finegrain.llm.rows import column, packed
from finegrain.operators.skew import join_group_facts
from finegrain.sources.staging import staged

KEY = "surrogate-key"
#: Draws after which entities that still collide are an error.
MOST_DRAWS = 24

# Given names by gender and script, for detection with those below and as surrogates.
GIVEN = {
    ("female", "latin"): ("Maria", "Elisabeth", "Katharina", "Sophie", "Margaret", "Victoria", "Patricia", "Jennifer", "Claudia", "Charlotte", "Isabel", "Camille", "Lucia", "Carmen", "Juliette", "Monika"),
    ("male", "latin"): ("Michael", "William", "Robert", "Thomas", "Alexander", "Christopher", "Frederick", "Wolfgang", "Philippe", "Jacques", "Carlos", "Miguel", "Francisco", "Matthew", "Joseph", "Klaus"),
    ("female", "cyrillic"): ("Мария", "Ольга", "Татьяна", "Екатерина", "Наталья", "Светлана", "Ирина", "Людмила"),
    ("male", "cyrillic"): ("Александр", "Дмитрий", "Сергей", "Владимир", "Николай", "Михаил", "Андрей", "Павел"),
    ("female", "greek"): ("Μαρία", "Ελένη", "Κατερίνα", "Σοφία", "Βασιλική", "Δήμητρα", "Αγγελική", "Γεωργία"),
    ("male", "greek"): ("Γιώργος", "Νίκος", "Δημήτρης", "Κώστας", "Παναγιώτης", "Βασίλης", "Χρήστος", "Αθανάσιος"),
}
# Endings of drawn given names by gender and script.
ENDINGS = {
    ("female", "latin"): ("a", "ia", "ina", "elle"), ("male", "latin"): ("o", "us", "an", "er"), ("any", "latin"): ("e", "is", "in", "y"),
    ("female", "cyrillic"): ("а", "ия", "ина", "на"), ("male", "cyrillic"): ("ий", "ан", "ор", "ей"), ("any", "cyrillic"): ("я", "и", "е", "о"),
    ("female", "greek"): ("α", "ια", "η", "ινα"), ("male", "greek"): ("ος", "ης", "ας", "ις"), ("any", "greek"): ("ω", "ι", "ε", "υ"),
}
# Further given names that are detected and never drawn as surrogates. Names that are common words as well are left out.
DETECTED = {
    ("female", "latin"): (
        "Anna Mary Linda Barbara Susan Jessica Sarah Karen Lisa Nancy Betty Sandra Ashley Emily Kimberly Donna Michelle Amanda Melissa Deborah Stephanie Rebecca Sharon Laura "
        "Cynthia Kathleen Amy Angela Shirley Brenda Emma Pamela Nicole Helen Samantha Katherine Catherine Christine Rachel Carolyn Janet Heather Diane Olivia Julie Kelly Lauren Christina "
        "Joan Evelyn Judith Andrea Hannah Megan Cheryl Jacqueline Martha Teresa Sara Janice Ann Kathryn Jean Abigail Alice Julia Judy Sophia Denise Doris Marilyn Danielle "
        "Beverly Theresa Diana Brittany Natalie Isabella Kayla Alexis Lori Jane Ruth Ellen Eleanor Lucy Eva Elena Irene Nora Clara Ursula Sabine Petra Renate Helga "
        "Karin Brigitte Ingrid Gisela Birgit Susanne Heike Martina Stefanie Anja Silke Ulrike Gabriele Angelika Kerstin Nicola Heidi Johanna Lena Lea Leonie Greta Hannelore Ilse "
        "Gertrud Hildegard Elke Jutta Antje Franziska Annika Katrin Britta Tanja Melanie Marlene Frieda Mathilde Marie Nathalie Isabelle Sylvie Valérie Véronique Sandrine Céline Aurélie Émilie "
        "Élodie Hélène Françoise Monique Nicolette Martine Chantal Chloé Manon Inès Léa Jeanne Margaux Océane Pauline Amélie Agnès Geneviève Odile Simone Yvette Colette Delphine Corinne "
        "Ana Josefa Cristina Beatriz Raquel Rocío Silvia Montserrat Alicia Lorena Natalia Sonia Yolanda Esther Marta Nuria Susana Verónica Ximena Valentina Daniela Gabriela Paula "
        "Lucía María José Ángela Inés"
    ).split(),
    ("male", "latin"): (
        "John James David Richard Charles Daniel Anthony Donald Steven Paul Andrew Joshua Kenneth Kevin Brian George Timothy Ronald Edward Jason Jeffrey Ryan Jacob Gary "
        "Nicholas Eric Jonathan Stephen Larry Justin Scott Brandon Benjamin Samuel Gregory Raymond Patrick Dennis Jerry Tyler Aaron Jose Adam Nathan Henry Douglas Zachary "
        "Peter Kyle Ethan Walter Noah Jeremy Keith Roger Terry Gerald Harold Sean Carl Arthur Lawrence Dylan Jesse Bryan Bruce Gabriel Albert Philip Vincent Elijah "
        "Louis Eugene Russell Oliver Liam Lucas Leo Simon Martin Hugh Stuart Graham Ian Neil Colin Hans Jürgen Uwe Günther Dieter Manfred Horst Helmut Heinz "
        "Gerhard Werner Karl Heinrich Friedrich Wilhelm Otto Hermann Ernst Kurt Fritz Bernd Rainer Jörg Matthias Andreas Stefan Markus Christoph Sebastian Florian Tobias Jan Felix "
        "Lukas Jonas Moritz Niklas Torsten Sven Holger Ralf Axel Detlef Volker Reinhard Rolf Siegfried Ulrich Johannes Johann Ludwig Konrad Günter Björn Lars Jens Dirk "
        "Jean Pierre Michel André Alain Bernard Gérard Patrice Nicolas Christophe Laurent Frédéric Stéphane Olivier Sébastien Julien Guillaume Antoine François Étienne Éric Thierry Pascal Bruno "
        "Didier Serge Yves Marcel Henri Hugues Gilles Luc Mathieu Benoît Rémi Cédric Jérôme Grégoire Maxime Théo Hugo Baptiste Raphaël Emmanuel Georges Lucien Fabrice Antonio "
        "Manuel José Juan Javier Luis Jesús Ángel Pedro Alejandro Rafael Fernando Pablo Jorge Ramón Sergio Enrique Andrés Vicente Diego Adrián Álvaro Raúl Iván Rubén "
        "Óscar Ignacio Joaquín Eduardo Roberto Jaime Alfonso Ricardo Emilio Gonzalo Julio Mariano Tomás Agustín Martín Nicolás Esteban Felipe Gustavo Hernán Rodrigo Alfredo Ernesto Mario "
        "Marcos Mateo"
    ).split(),
    ("female", "cyrillic"): (
        "Анна Елена Юлия Анастасия Виктория Дарья Марина Галина Валентина Нина Лариса Тамара Алла Оксана Ксения Евгения Полина Софья Алиса Кристина Маргарита Валерия Зоя Лидия "
        "Раиса Жанна Инна"
    ).split(),
    ("male", "cyrillic"): (
        "Иван Алексей Максим Артём Артем Евгений Виктор Игорь Юрий Олег Антон Денис Никита Кирилл Илья Василий Пётр Петр Константин Вячеслав Станислав Виталий Анатолий Валерий "
        "Борис Геннадий Григорий Леонид Фёдор Федор Степан Тимофей Егор Семён Семен Ярослав Глеб Георгий Аркадий Эдуард"
    ).split(),
}
# Titles by gender ("" where either).
TITLES = {"Mr": "male", "Mrs": "female", "Ms": "female", "Miss": "female", "Herr": "male", "Frau": "female", "Monsieur": "male", "Madame": "female", "Señor": "male", "Señora": "female", "Dr": "", "Prof": ""}
# Syllables of surrogate family names.
SYLLABLES = {
    "latin": ("bar", "ben", "cal", "dor", "fel", "gar", "hol", "jen", "kas", "lin", "mar", "nor", "pel", "quin", "ros", "sel", "tor", "ul", "ven", "wal", "yar", "zel", "bri", "cro", "dra", "fro", "gri", "kra", "pla", "sta", "tru", "wen"),
    "cyrillic": ("бел", "вор", "гор", "дан", "зел", "кол", "лан", "мир", "нов", "пет", "рос", "сол", "тар", "фед", "хар", "чер"),
    "greek": ("βασ", "γορ", "δελ", "ζαν", "θερ", "καλ", "λαμ", "μαν", "νικ", "παν", "ροδ", "σταμ", "ταρ", "φιλ", "χαρ", "ψαρ"),
}
# Words before which two or three capitalised words are a person.
CUES = ("my name is", "My name is", "his name is", "her name is", "is called", "Name:", "Author:", "Contact:", "Signed,", "Sincerely,", "Regards,", "je m'appelle", "Je m'appelle", "ich heiße", "Ich heiße", "mein Name ist", "Mein Name ist", "me llamo", "Me llamo", "mi nombre es", "Mi nombre es", "меня зовут", "Меня зовут", "με λένε", "Με λένε")

_NAME = r"\p{Lu}\p{Ll}+"
_KNOWN = {n: gender for table in (DETECTED, GIVEN) for (gender, _), names in table.items() for n in names}
#: All known given names, tried by first letter only.
_GIVEN_ALL = "|".join(f"{first}(?:{'|'.join(sorted((n[1:] for n in _KNOWN if n[0] == first), key=len, reverse=True))})" for first in sorted({n[0] for n in _KNOWN}))
_TITLE_ALL = "|".join(sorted(TITLES, key=len, reverse=True))
#: Telephone numbers of groups of 3, 3 and 4 digits, and any with a plus sign and 7 to 15 digits; country codes.
_GROUPED = r"(?<![\d+])(?:\+\d{1,3}[ .-]?)?(?:\(\d{3}\)|\d{3})[ .-]\d{3}[ .-]\d{4}(?!\d)"
_ABROAD = r"(?<![\p{L}\d+])\+(?:[ ./()-]{0,2}\d){7,15}(?!\d)"
_COUNTRY = r"^\+[ (]{0,2}(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3})"
_CUED = f"(?={_NAME} {_NAME})(?:(?<=(?:{'|'.join(CUES)})[ \\n])|(?<=Dear )(?={_NAME}(?: {_NAME}){{1,2}},)|(?={_NAME} {_NAME} ?[<(][\\p{{L}}\\p{{N}}._%+-]{{1,64}}@)){_NAME}(?: {_NAME}){{1,2}}"
#: Patterns by type, in order of precedence. No group repeats without a bound: the engine recurses for each turn of a group.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]{1,256}+@(?:[\p{L}\p{N}-]{1,63}+\.){1,126}\p{L}{2,}",
    "secret": r"(?<![\p{L}\p{N}])(?i:password|passwd|pwd|token|secret|api[_-]?key)\s{0,3}[=:]\s{0,3}\"?[A-Za-z0-9+/_-]{8,}+\"?",
    "access_key": r"(?<![A-Za-z0-9])A[KS]IA[A-Z0-9]{16}(?![A-Za-z0-9])",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)\.){3}(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)(?!\d|\.\d)",
    "phone": rf"{_GROUPED}|{_ABROAD}",
    "card": r"(?<![\p{L}\d])(?:\d{4}[ -]\d{4}[ -]\d{4}[ -]\d{4}|\d{13,19})(?![\p{L}\d])",
    "person": rf"(?<!\p{{L}})(?:(?:{_TITLE_ALL})\.? (?:{_NAME} )?{_NAME}|(?={_NAME} {_NAME})(?:(?:{_GIVEN_ALL}) ){{1,3}}{_NAME}|{_CUED})(?!\p{{L}})",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Numbers that issuers give out, by prefix and length.
_ISSUED = r"^(?:4(?:\d{12}|\d{15}|\d{18})|5[1-5]\d{14}|2[2-7]\d{14}|3[47]\d{13}|3(?:0[0-5]|[689]\d)\d{11,16}|35\d{14}|6(?:011|4[4-9]\d|5\d\d|2\d\d)\d{12,15}|(?:50|5[6-9]|6\d)\d{11,17})$"
#: Shapes one of which every entity holds: a cheap test before the patterns.
TELLING = r"[@=:]|\d{3}|\+[ (]{0,2}\d|\d\.\d|A[KS]IA|\p{Lu}\p{Ll}+\.? \p{Lu}"


def _digest(kind: Column, value: Column, attempt: Column, key: str) -> Column:
    """128 hexadecimal digits from the key, the entity and the attempt."""
    return F.sha2(F.encode(F.concat_ws("\u0001", F.lit(key), kind, value, attempt.cast("string")), "UTF-8"), 512)


# Surrogates are SQL text: one expression of many small steps, put together here and parsed once.


def _draw(digest: str, at: str, below: int) -> str:
    """The digest's ``at``-th number (four digits each, 32 of them, then again), modulo ``below``."""
    return f"cast(pmod(cast(conv(substring({digest}, pmod({at}, 32) * 4 + 1, 4), 16, 10) as bigint) + cast(floor(({at}) / 32) as bigint) * 7, {below}) as int)"


def _letter(letters: str, digest: str, at: str) -> str:
    return f"substring('{letters}', {_draw(digest, at, len(letters))} + 1, 1)"


def _word(words, digest: str, at: str) -> str:
    return f"element_at(split('{' '.join(words)}', ' '), {_draw(digest, at, len(words))} + 1)"


def _alike(text: str, digest: str, hexadecimal: bool = False) -> str:
    """Every character replaced by one of its own kind: digit, lower or upper letter of its script; others stay."""
    cyrillic, greek = "абвгдежзиклмнопрстуфхцчшэюя", "αβγδεζηθικλμνξοπρστυφχψω"
    alphabets = [
        (r"[0-9]", "0123456789"), (r"[a-z]", "abcdefghijklmnopqrstuvwxyz"), (r"[A-Z]", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
        (r"[\p{IsCyrillic}&&\p{Lu}]", cyrillic.upper()), (r"\p{IsCyrillic}", cyrillic), (r"[\p{IsGreek}&&\p{Lu}]", greek.upper()), (r"\p{IsGreek}", greek),
        (r"\p{Lu}", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"), (r"\p{L}", "abcdefghijklmnopqrstuvwxyz"),
    ]
    cases = f"when c rlike '[a-f]' then {_letter('abcdef', digest, 'i')} " if hexadecimal else ""
    cases += " ".join(f"when c rlike r'{pattern}' then {_letter(letters, digest, 'i')}" for pattern, letters in alphabets)
    return f"array_join(transform(split({text}, ''), (c, i) -> case {cases} else c end), '')"


def _more(digest: str, count: str, letters: str) -> str:
    """``count`` further letters, none where it is not positive."""
    return f"if({count} > 0, array_join(transform(sequence(1, greatest({count}, 1)), k -> {_letter(letters, digest, 'k + 24')}), ''), '')"


def _syllables(script: str, digest: str, count: str) -> str:
    return f"array_join(transform(sequence(1, {count}), k -> {_word(SYLLABLES[script], digest, 'k')}), '')"


def _script_sql(value: str) -> str:
    return f"case when {value} rlike r'\\p{{IsCyrillic}}' then 'cyrillic' when {value} rlike r'\\p{{IsGreek}}' then 'greek' else 'latin' end"


def _name_like(value: str, digest: str, attempt: str) -> str:
    """A family name of the same script: four syllables, and one more for every attempt."""
    return f"case {_script_sql(value)} " + " ".join(f"when '{script}' then initcap({_syllables(script, digest, f'{attempt} + 4')})" for script in SYLLABLES) + " end"


def _given_like(kind: str, digest: str, attempt: str) -> str:
    """A given name of the gender and script that ``kind`` names: a listed one, and after the first attempt a drawn one behind it."""
    cases = []
    for (gender, script), endings in ENDINGS.items():
        listed = _word(GIVEN.get((gender, script)) or GIVEN["female", script] + GIVEN["male", script], digest, "0")
        drawn = f"initcap(concat({_syllables(script, digest, f'{attempt} + 1')}, {_word(endings, digest, '31')}))"
        cases.append(f"when 'given:{gender}:{script}' then if({attempt} = 0, {listed}, concat({listed}, '-', {drawn}))")
    return f"case {kind} {' '.join(cases)} end"


def _luhn(number: str) -> str:
    """The Luhn sum of a string of digits, modulo 10."""
    twice = "cast(c as int) * 2"
    return f"pmod(aggregate(transform(reverse(split({number}, '')), (c, i) -> if(i % 2 = 1, {twice} % 10 + cast(floor({twice} / 10) as int), cast(c as int))), 0, (a, x) -> a + x), 10)"


def _with_check_digit(head: str, model: str) -> str:
    """``head`` with the digit behind it that makes it a valid card number, as ``model`` is (or no valid one where it is none)."""
    short = f"pmod(10 - {_luhn(f'concat({head}, 0)')}, 10)"
    other = f"pmod({short} + 1 + pmod(crc32(encode({head}, 'UTF-8')), 9), 10)"
    return f"concat({head}, cast(if({_luhn(model)} = 0, {short}, {other}) as string))"


def surrogate_sql(kind: str = "kind", value: str = "value", attempt: str = "attempt", digest: str = "digest") -> str:
    """The canonical surrogate of a canonical value, from its digest (a column that is there: every character draws from it). Names and
    addresses get longer with the attempt, other values after some."""
    lower, d = "abcdefghijklmnopqrstuvwxyz", digest
    domain = f"substring_index({value}, '@', -1)"
    host = f"concat({_alike(f"substring_index({domain}, '.', 1)", f'reverse({d})')}, '.example.com')"
    address = f"concat({_alike(f"substring_index({value}, '@', 1)", d)}, {_more(d, attempt, lower)}, '@', if({domain} rlike '(^|[.])example[.](com|org|net)$', {domain}, {host}))"
    octets = f"concat_ws('.', {', '.join(f'cast({_draw(d, str(k), 254)} + 1 as string)' for k in range(4))})"
    # telephone: no leading 0 or 1
    phone = f"concat(cast({_draw(d, '31', 8)} + 2 as string), substring({_alike(value, d)}, 2), {_more(d, f'{attempt} - 4', '0123456789')})"
    card = _with_check_digit(f"concat(substring({value}, 1, 1), substring({_alike(value, d)}, 2, length({value}) - 2))", value)
    # what holds for the whole value is asked outside the loop over its characters
    secret = f"concat(if({value} rlike '^[0-9a-f]+$', {_alike(value, d, True)}, {_alike(value, d)}), {_more(d, f'{attempt} - 4', '0123456789')})"
    key = f"concat(substring({value}, 1, 4), substring({_alike(value, d)}, 5))"
    return (
        f"case when {kind} = 'email' then {address} when {kind} = 'ip' then {octets} when {kind} = 'phone' then {phone} when {kind} = 'card' then {card} "
        f"when {kind} = 'secret' then {secret} when {kind} = 'access_key' then {key} when {kind} like 'given:%' then {_given_like(kind, d, attempt)} else {_name_like(value, d, attempt)} end"
    )


def mentions(text: Column) -> Column:
    """All mentions in order: an array of strings (empty for null)."""
    found = F.when(text.rlike(TELLING), F.regexp_extract_all(text, F.lit(ANY), F.lit(0)))
    return F.coalesce(found, F.array().cast("array<string>"))


def _kind() -> Column:
    """The type of the mention ``surface``; ``none`` for digits that are no card number."""
    surface, digits = F.col("surface"), "regexp_replace(surface, '[^0-9]', '')"
    out = F.when(F.lit(False), F.lit(""))
    for kind, pattern in PATTERNS.items():
        value = F.when(F.expr(digits).rlike(_ISSUED) & (F.expr(_luhn(digits)) == 0), "card").otherwise("none") if kind == "card" else F.lit(kind)
        out = out.when(surface.rlike(f"^(?:{pattern})$"), value)
    return out.otherwise("person")  # what only its surroundings make a person


def _parts(kind: Column, surface: Column) -> Column:
    """The entities of a mention: an array of (kind, canonical value, gender where the mention tells it)."""
    entity = lambda k, v, g: F.struct(k.alias("kind"), v.alias("value"), g.alias("gender"))
    nothing = F.lit(None).cast("string")
    value = (
        F.when(kind == "email", F.lower(surface))
        .when(kind == "secret", F.regexp_extract(surface, r"[=:]\s*\"?([^\"]+)\"?$", 1))
        .when((kind == "phone") & surface.rlike(f"^(?:{_GROUPED})$"), F.substring(F.regexp_replace(surface, r"\D", ""), -10, 10))
        .when(kind == "phone", F.regexp_replace(F.regexp_replace(surface, _COUNTRY, ""), r"\D", ""))
        .when(kind == "card", F.regexp_replace(surface, r"\D", ""))
        .otherwise(surface)
    )
    title = F.regexp_extract(surface, rf"^({_TITLE_ALL})\.? ", 1)
    words = F.split(F.regexp_replace(surface, rf"^(?:{_TITLE_ALL})\.? ", ""), " ")
    titles = F.create_map(*(F.lit(x) for kv in TITLES.items() for x in kv))
    known = F.from_json(F.lit(json.dumps(_KNOWN)), "map<string, string>")

    def name(w: Column, i: Column) -> Column:
        told = F.try_element_at(known, w)
        gender = F.coalesce(told, F.nullif(F.try_element_at(titles, title), F.lit("")))
        given = F.when(F.size(words) == 1, told.isNotNull()).otherwise((i < F.size(words) - 1) & ((i == 0) | told.isNotNull()))
        return entity(F.when(given, "given").otherwise("family"), w, F.when(given, gender))

    return F.when(kind == "person", F.transform(words, name)).otherwise(F.array(entity(kind, value, nothing)))


def _written(kind: Column, surface: Column, value: Column, new: Column) -> Column:
    """A surrogate in the mention's format."""
    digits = F.regexp_replace(surface, r"\D", "")
    lead = F.length(digits) - F.length(value)  # digits before the value: a country code, kept
    numbered = F.array_join(
        F.transform(
            F.split(surface, ""),
            lambda c, i: F.when(
                c.rlike(r"\d"),
                F.coalesce(_char_at(new, F.length(F.regexp_replace(F.substring(surface, F.lit(1), i + 1), r"\D", "")) - lead), c),
            ).otherwise(c),
        ),
        "",
    )
    longer = F.substring(new, F.length(value) + 1, F.lit(40))  # digits of a longer surrogate
    loud = (F.upper(surface) == surface) & (F.lower(surface) != surface)
    return (
        F.when(kind.isin("phone", "card"), F.concat(numbered, longer))
        .when(kind == "secret", F.replace(surface, value, new))
        .when((kind == "email") & loud, F.upper(new))
        .otherwise(new)
    )


def _char_at(text: Column, at: Column) -> Column:
    return F.when(at >= 1, F.substring(text, at, F.lit(1)))


def assign_surrogates(entities: DataFrame, key: str = KEY, most_draws: int = MOST_DRAWS) -> DataFrame:
    """``(kind, value, new)`` for distinct ``(kind, value)``: distinct, none a real value of its kind, none with its own value in it.

    A given name's kind is ``given:<gender>:<script>``; given names of all kinds are one kind to the checks.
    """
    sort = F.substring_index("kind", ":", 1)
    digest = _digest(F.col("kind"), F.col("value"), F.col("attempt"), key)
    real = staged(entities.select("kind", "value").distinct().select("kind", "value", sort.alias("sort"), F.lit(0).alias("attempt")).withColumn("digest", digest), "entities")
    pending = real
    taken = real.select("sort", F.lower("value").alias("low")).distinct()
    settled, new = None, F.expr(surrogate_sql())
    for _ in range(most_draws):
        drawn = pending.withColumn("new", new).drop("digest").withColumn("low", F.lower("new"))
        drawn = staged(drawn.withColumn("own", F.contains("low", F.lower("value"))), "drawn")
        first = drawn.filter("not own").groupBy("sort", "low").agg(F.min(F.struct("kind", "value")).alias("first"))
        checked = drawn.join(first, ["sort", "low"], "left").join(taken.withColumn("held", F.lit(True)), ["sort", "low"], "left")
        good = ~F.col("own") & F.col("held").isNull() & (F.struct("kind", "value") == F.col("first"))
        checked = checked.withColumn("good", F.coalesce(good, F.lit(False))).select("kind", "value", "sort", (F.col("attempt") + 1).alias("attempt"), "new", "low", "good")
        checked = staged(checked.withColumn("digest", F.when(~F.col("good"), digest)), "draws")
        done = checked.filter("good")
        settled = done.select("kind", "value", "new") if settled is None else settled.unionByName(done.select("kind", "value", "new"))
        taken = taken.unionByName(done.select("sort", "low"))
        pending = checked.filter("not good").select("kind", "value", "sort", "attempt", "digest")
        if not pending.limit(1).count():
            return settled
    raise RuntimeError(f"entities of kind {pending.first()['kind']} found no surrogate of their own in {most_draws} draws")


def with_surrogates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", key: str = KEY) -> DataFrame:
    """``docs`` with every entity of ``text`` replaced, ``n_entities`` and ``entity_kinds`` (sorted, comma-joined)."""
    docs = docs.drop(*(c for c in ("n_entities", "entity_kinds") if c != text))
    doc_key = F.xxhash64(column(id_col), F.coalesce(column(text), F.lit("")))
    found = docs.select(doc_key.alias("doc"), mentions(column(text)).alias("found"))
    spots = staged(found.filter(F.size("found") > 0).dropDuplicates(["doc"]), "mentions")
    at = staged(spots.select("doc", F.posexplode("found").alias("at", "surface")).withColumn("type", _kind()), "typed-mentions")
    parts = at.filter("type != 'none'").select("doc", "at", "surface", "type", F.posexplode(_parts(F.col("type"), F.col("surface"))).alias("part", "e"))
    parts = staged(parts.select("doc", "at", "part", "surface", "type", "e.kind", "e.value", "e.gender"), "entity-mentions")
    counted = parts.groupBy("kind", "value").agg(F.count("*").alias("weight"), F.min("gender").alias("lo"), F.max("gender").alias("hi"))
    gender = F.when(F.col("lo") == F.col("hi"), F.col("lo")).otherwise("any")
    whole_kind = F.when(F.col("kind") == "given", F.concat_ws(":", "kind", gender, F.expr(_script_sql("value")))).otherwise(F.col("kind"))
    counted = staged(counted.select(F.concat_ws("\u0001", "kind", "value").alias("entity"), whole_kind.alias("kind"), "value", "weight"), "entity-counts")
    table = assign_surrogates(counted, key)
    facts = staged(counted.join(table, ["kind", "value"]).select("entity", "new", "weight"), "surrogates")
    rows = parts.withColumn("entity", F.concat_ws("\u0001", "kind", "value"))
    joined = join_group_facts(rows, facts, "entity", "weight", parts.count(), "doc")
    written = joined.withColumn("put", F.when(F.col("type") == "person", F.col("new")).otherwise(_written(F.col("type"), F.col("surface"), F.col("value"), F.col("new"))))
    # one document's mentions: as many rows as it has
    by_mention = written.groupBy("doc", "at").agg(F.first("surface").alias("surface"), F.first("type").alias("type"), F.array_sort(F.collect_list(F.struct("part", "put"))).alias("puts"))
    names = F.array_join(F.transform("puts", lambda p: p["put"]), " ")
    whole = F.when(F.col("type") == "person", F.concat(F.regexp_extract("surface", rf"^(?:{_TITLE_ALL})\.? ", 0), names)).otherwise(F.col("puts")[0]["put"])
    # what has the shape of an entity and is none stays as it was
    others = at.filter("type = 'none'").select("doc", "at", F.lit(None).cast("string").alias("type"), F.col("surface").alias("put"))
    lists = by_mention.select("doc", "at", "type", whole.alias("put")).unionByName(others).groupBy("doc").agg(
        F.array_sort(F.collect_list(F.struct("at", "put"))).alias("puts"), F.array_join(F.array_sort(F.collect_set("type")), ",").alias("kinds"), F.count("type").alias("n")
    )
    lists = staged(lists.filter("n > 0"), "replacements")
    # rows without an entity pass straight through
    return _rewritten(docs, doc_key, text, lists)


def _rewritten(docs: DataFrame, doc_key: Column, text: str, lists: DataFrame) -> DataFrame:
    """``docs`` with the replacements of ``lists`` in their texts."""
    own = [c for c in ("n_entities", "entity_kinds") if c != text]
    facts = {"n_entities": "n", "entity_kinds": "kinds"}
    plain, maybe = split_by_keys(packed(docs, doc=doc_key), lists, "doc")
    body = F.col("row").getField(text)
    plain = plain.select("row", body.alias("body"), F.lit(0).cast("long").alias("n"), F.lit("").alias("kinds"))
    touched = maybe.join(lists, "doc", "left").withColumn("old", body)
    pieces = F.transform("puts", lambda p: p["put"])
    mixed = F.array_join(F.zip_with(F.split("old", F.lit(ANY), -1), pieces, lambda s, p: F.concat(F.coalesce(s, F.lit("")), F.coalesce(p, F.lit("")))), "")
    touched = touched.select("row", F.when(F.col("puts").isNull(), F.col("old")).otherwise(mixed).alias("body"), F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.coalesce("kinds", F.lit("")).alias("kinds"))
    columns = [F.col("body").alias(c) if c == text else F.col("row").getField(c).alias(c) for c in docs.columns]
    return plain.unionByName(touched).select(*columns, *(F.col(facts[c]).alias(c) for c in own))
