"""PII surrogates: every detected entity gets a keyed replacement of its own type and shape.

Mentions are found by one expression of alternatives, typed, and brought to a canonical form (an
address in lower case, a number's digits, a name's capitals), so mentions of one entity that are written differently
stay one entity. The table of distinct entities is given surrogates from a keyed hash, attempt by
attempt: a surrogate that another entity has, or that is itself an entity of the corpus, is
refused and its entity tries again with more room, so distinct entities stay distinct, however many. Each mention is then
written in its own format: digits for digits, letters for letters of the same script and case, valid check digits where
there were. Names are replaced word by word, given names by ones of the gender that the title shows, so their number of
words, hyphens and case stay, and a person named in part or in full stays one. In a text that names people after
titles, their words are mentions wherever else they stand in it; words that no title of the text precedes are not found.

Everything is built-in expressions. The lists of mentions of a text, not the texts, are what is
joined; equal lists are worked once.

Defined results: a null text stays null; texts without entities are returned untouched; repeated rows
stay repeated; an empty table gives an empty one. Columns other than the text are kept as they are.
"""

from __future__ import annotations

from functools import reduce
from itertools import count

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from celldiv.llm.common import let, persisted

FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "Госпожа")
MALE = ("Mr", "Herr", "Monsieur", "Señor", "Sr", "Господин")
NEUTRAL = ("Dr", "Prof")
KEYWORDS = ("password", "passwd", "pwd", "token", "secret", "api_key", "apikey", "access_key")


def _any_case(words: tuple[str, ...]) -> str:
    """Alternatives that match the words in any case. Letter classes, not flags: just what lower() folds to the words."""
    return "|".join("".join(f"[{c.lower()}{c.upper()}]" if c.isalpha() else c for c in w) for w in words)


TITLES = _any_case((*FEMALE, *MALE, *NEUTRAL))
_NAME = r"\p{Lu}[\p{L}'’\-]+"
#: Patterns by type, tried in this order at each place. No capturing groups: the whole match is the mention.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+\-])[\p{L}\p{N}._%+\-]++@(?:[\p{L}\p{N}\-]+\.)+\p{L}{2,}",
    "secret": rf"(?<=[=:\s\"'])(?=[A-Za-z0-9+/_\-]{{8}})(?<=[=:]\s{{0,2}}[\"']?)(?<=(?:{_any_case(KEYWORDS)})\s{{0,2}}[=:]\s{{0,2}}[\"']?)[A-Za-z0-9+/_\-]{{8,}}|(?<![\p{{L}}\p{{N}}])AKIA[0-9A-Z]{{16}}(?![\p{{L}}\p{{N}}])|(?<![\p{{L}}\p{{N}}])(?=[0-9a-fA-F]{{40}}(?![\p{{L}}\p{{N}}]))(?=[0-9a-fA-F]{{0,39}}[0-9])[0-9a-fA-F]{{40}}",
    "ip": r"(?<![\p{L}\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?![\p{L}\d])(?!\.\d)",
    "phone": r"(?<![\p{L}\d+])(?:\+\d{1,3}[ .\-]?)?\(\d{2,4}\)[ .\-]?\d{3,4}[ .\-]?\d{3,4}(?![\p{L}\d])|(?<![\p{L}\d+])\+\d{1,3}(?:[ .\-]?\d{2,4}){2,5}(?![\p{L}\d])|(?<![\p{L}\d+\-])\d{3}-\d{3}-\d{4}(?![\p{L}\d\-])",
    "ssn": r"(?<![\p{L}\d\-])\d{3}-\d{2}-\d{4}(?![\p{L}\d\-])",
    "iban": r"(?<![\p{L}\d])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\d])",
    "account": r"(?<![\p{L}\d.\-])(?:\d[ \-]?){12,18}\d(?![\p{L}\d])",
    "name": rf"(?<=[ \x{{A0}}])(?=\p{{Lu}})(?<=\b(?:{TITLES})\.?[ \x{{A0}}]){_NAME}(?: {_NAME}){{0,2}}",
}
#: No mention starts after a letter or a digit, so the places inside words are left at once. Its other lookaheads and short lookbehinds
#: before the long ones only refuse places early, too.
PATTERN = r"(?<![\p{L}\d])(?:" + "|".join(f"(?:{p})" for p in PATTERNS.values()) + ")"
#: What a text with a secret or a name without digits has, in lower case.
CUES = (*KEYWORDS, "akia", *(t.lower() for t in (*FEMALE, *MALE, *NEUTRAL)))

LATIN, CYRILLIC, GREEK = "abcdefghijklmnopqrstuvwxyz", "абвгдежзийклмнопрстуфхцчшщыэюя", "αβγδεζηθικλμνξοπρστυφχψω"
#: Bytes of all distinct lists of mentions and their surrogates up to which they are broadcast.
BROADCAST_BYTES = 48_000_000
#: So many attempts keep a format's length.
ROOMY = 9
GIVEN = {
    ("latin", "f"): ("Anna", "Clara", "Elena", "Julia", "Laura", "Maria", "Nora", "Sofia"),
    ("latin", "m"): ("Adam", "David", "Felix", "Jonas", "Lukas", "Martin", "Paul", "Simon"),
    ("cyrillic", "f"): ("Анна", "Вера", "Елена", "Ирина", "Мария", "Нина", "Ольга", "Софья"),
    ("cyrillic", "m"): ("Антон", "Борис", "Иван", "Лев", "Марк", "Олег", "Павел", "Юрий"),
    ("greek", "f"): ("Άννα", "Ελένη", "Ειρήνη", "Ιωάννα", "Κατερίνα", "Μαρία", "Σοφία", "Χριστίνα"),
    ("greek", "m"): ("Αλέξης", "Ανδρέας", "Γιάννης", "Δημήτρης", "Κώστας", "Μάρκος", "Νίκος", "Πέτρος"),
}
SYLLABLES = {"latin": ("ba", "den", "kor", "la", "mi", "nor", "ris", "sel", "ta", "ven", "wil", "zan", "ho", "gar", "fel", "dor"),
             "cyrillic": ("ба", "ден", "кор", "ла", "ми", "нор", "рис", "сел", "та", "вен", "вил", "зан", "хо", "гар", "фел", "дор"),
             "greek": ("βα", "δεν", "κορ", "λα", "μι", "νορ", "ρισ", "σελ", "τα", "βεν", "βιλ", "ζαν", "χο", "γαρ", "φελ", "δορ")}
#: Endings of made-up given names, and of family names after a title, by script and gender; n is neither.
ENDINGS = {"latin": {"f": "a", "m": "us", "n": ""}, "cyrillic": {"f": "а", "m": "", "n": ""}, "greek": {"f": "α", "m": "ος", "n": ""}}
FAMILY_ENDINGS = {"latin": {"f": "", "m": "", "n": ""}, "cyrillic": {"f": "ова", "m": "ов", "n": "ов"}, "greek": {"f": "ου", "m": "ης", "n": "ης"}}
#: A word of a name; what stands between words (spaces, hyphens) is kept.
NAME_WORD = r"[\p{L}'’]+"


def _has_any(text: Column, words: tuple[str, ...]) -> Column:
    """Whether the text has one of the lower-case words in any case; it is folded once."""
    return let(F.lower(text), lambda low: reduce(lambda a, b: a | b, [low.contains(w) for w in words]))


def titled(text: Column) -> Column:
    return _has_any(text, tuple(t.lower() for t in (*FEMALE, *MALE, *NEUTRAL)))


def gate(text: Column) -> Column:
    """A cheap test that any text with a mention passes: plain searches, no backtracking."""
    return text.rlike("[0-9@]") | _has_any(text, CUES)


def _titled_names(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(rf"\b(?:{TITLES})\.?[ \x{{A0}}]{_NAME}(?: {_NAME}){{0,2}}"), F.lit(0))


def _untitled(title_and_name: Column) -> Column:
    return F.regexp_replace(title_and_name, rf"^(?:{TITLES})\.?[ \x{{A0}}]", "")


def pattern_of(text: Column) -> Column:
    """The pattern for one text: where it names people after titles, their words count as mentions wherever else they stand."""
    words = F.array_distinct(F.flatten(F.transform(_titled_names(text), lambda t: F.regexp_extract_all(_untitled(t), F.lit(NAME_WORD), F.lit(0)))))
    long = F.filter(words, lambda w: F.char_length(w) > 2)
    # as they are written, and with only the first letter or all letters large
    forms = F.array_distinct(F.flatten(F.transform(long, lambda w: F.array(w, F.initcap(w), F.upper(w)))))
    other = lambda some: F.concat(F.lit(PATTERN[:-1] + r"|(?:"), F.array_join(some, "|"), F.lit(rf")(?![\p{{L}}\p{{N}}'’])(?:[ \-](?:"), F.array_join(some, "|"), F.lit(r")(?![\p{L}\p{N}'’]))*)"))
    return F.when(titled(text), let(forms, lambda some: F.when(F.size(some) > 0, other(some)).otherwise(F.lit(PATTERN)))).otherwise(F.lit(PATTERN))


def has_mention(text: Column) -> Column:
    """Stops at the first mention; false for null. Filters use it so that only texts with mentions are extracted from."""
    return F.coalesce(gate(text) & text.rlike(PATTERN), F.lit(False))


def cut_texts(docs: DataFrame, text: str, *others: str) -> DataFrame:
    """Of texts that have a mention, kept: the named columns, __m (the mentions), __rest (what stands between them), __g (the words of titled
    names). Each text is searched once for all that follows; these are few of the texts."""
    t, none = F.col(text), F.array().cast("array<string>")
    both = let(pattern_of(t), lambda p: F.struct(F.coalesce(F.regexp_extract_all(t, p, F.lit(0)), none).alias("m"), F.split(t, p, -1).alias("rest")))
    cut = docs.where(has_mention(t)).select(*others, both.alias("__x"), F.when(titled(t), _gender(t)).alias("__g"))
    return persisted(cut.select(*others, F.col("__x.m").alias("__m"), F.col("__x.rest").alias("__rest"), "__g"))


def parts_of(mention: Column, kind: Column) -> Column:
    """A name's words, each an entity (so a person named in part or in full stays one), with what stands before and after; other mentions whole."""
    words = F.regexp_extract_all(mention, F.lit(NAME_WORD), F.lit(0))
    gaps = F.split(mention, NAME_WORD, -1)
    cut = let(F.struct(words.alias("w"), gaps.alias("g")), lambda x: F.transform(x["w"], lambda w, i: F.struct(
        w.alias("part"), F.get(x["g"], i).alias("before"), F.when(i == F.size(x["w"]) - 1, F.get(x["g"], i + 1)).otherwise(F.lit("")).alias("after"))))
    return F.when(kind == "name", cut).otherwise(F.array(F.struct(mention.alias("part"), F.lit("").alias("before"), F.lit("").alias("after"))))


def kind_of(mention: Column) -> Column:
    """The first type that matches the whole mention; what only its surroundings told are secrets and names."""
    out = F.lit("secret")
    bare = {"name": rf"^{_NAME}(?:[ \-]{_NAME})*$"} | {k: f"^(?:{PATTERNS[k]})$" for k in ("account", "iban", "ssn", "phone", "ip", "email")}
    for kind, pattern in bare.items():
        out = F.when(mention.rlike(pattern), F.lit(kind)).otherwise(out)
    return F.when(mention.rlike(r"^AKIA[0-9A-Z]{16}$"), F.lit("secret")).otherwise(out)


def _country(mention: Column) -> Column:
    """A phone's country code as written, which its surrogate keeps."""
    return F.regexp_extract(mention, r"^\+\d{1,3}(?=[ .\-(])", 0)


def _national(kind: Column, mention: Column) -> Column:
    return F.when(kind == "phone", F.substr(mention, F.char_length(_country(mention)) + 1, F.char_length(mention))).otherwise(mention)


def canonical(kind: Column, mention: Column) -> Column:
    return (F.when(kind.isin("phone", "account", "ssn"), F.regexp_replace(_national(kind, mention), r"\D", ""))
            .when(kind == "email", F.lower(mention)).when(kind == "iban", F.regexp_replace(mention, " ", "")).when(kind == "name", F.initcap(mention)).otherwise(mention))


def _stream(key: str, kind: Column, form: Column, attempt: int) -> Column:
    """128 keyed hex digits of the entity."""
    told = lambda n: F.sha2(F.concat_ws("\x1f", F.lit(key), kind, form, F.lit(str(attempt)), F.lit(str(n))).cast("binary"), 256)
    return F.concat(told(0), told(1))


def _pick(stream: Column, at: int, choices: tuple[str, ...] | str) -> Column:
    values = F.array(*[F.lit(c) for c in choices])
    return F.element_at(values, (F.pmod(F.conv(F.substring(stream, at, 4), 16, 10).cast("int"), F.lit(len(choices))) + 1).cast("int"))


def _shaped(form: Column, stream: Column, hexadecimal: Column) -> Column:
    """form with every letter and digit replaced by one of its own class."""
    def letter(c: Column, v: Column) -> Column:
        lower = c == F.lower(c)
        small = c.rlike("[a-f]") | (form == F.lower(form))  # a hexadecimal digit may become a letter: in the case of the others
        some = lambda letters: F.when(lower, F.element_at(F.array(*[F.lit(x) for x in letters]), F.pmod(v, F.lit(len(letters))) + 1)).otherwise(F.element_at(F.array(*[F.lit(x.upper()) for x in letters]), F.pmod(v, F.lit(len(letters))) + 1))
        plain = F.when(c.rlike(r"\p{IsCyrillic}"), some(CYRILLIC)).when(c.rlike(r"\p{IsGreek}"), some(GREEK)).otherwise(some(LATIN))
        return F.when(hexadecimal & c.rlike("[0-9a-fA-F]"), F.when(lower & small, F.lower(F.hex(F.pmod(v, F.lit(16))))).otherwise(F.hex(F.pmod(v, F.lit(16))))).when(c.rlike("[0-9]"), F.pmod(v, F.lit(10)).cast("string")).when(c.rlike(r"\p{L}"), plain).otherwise(c)

    value = lambda i: F.conv(F.substring(stream, F.pmod(i * 3, F.lit(124)) + 1, 4), 16, 10).cast("int")
    return F.array_join(F.transform(F.split(form, ""), lambda c, i: letter(c, value(i))), "")


def luhn_sum(digits: Column) -> Column:
    """The check sum of a number, from the right."""
    def add(s: Column, x: Column) -> Column:
        d = x["c"] * F.when(F.pmod(x["i"], F.lit(2)) == 1, 2).otherwise(1)
        return s + F.when(d > 9, d - 9).otherwise(d)

    right = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.struct(c.cast("int").alias("c"), i.alias("i")))
    return F.aggregate(right, F.lit(0), add)


def iban_rest(iban: Column) -> Column:
    """The check number of an IBAN: the remainder by 97 of its digits, letters as 10 to 35, from the fifth character on, the first four last."""
    turned = F.concat(F.substr(iban, F.lit(5), F.char_length(iban)), F.substring(iban, 1, 4))

    def add(s: Column, c: Column) -> Column:
        v = F.when(c.rlike("[0-9]"), c.cast("int")).otherwise(F.ascii(c) - 55)
        return F.pmod(s * F.when(v > 9, 100).otherwise(10) + v, F.lit(97))

    return F.aggregate(F.filter(F.split(turned, ""), lambda c: c != ""), F.lit(0), add)


def _surrogate(kind: Column, form: Column, hint: Column, key: str, attempt: int) -> Column:
    """The canonical form of the replacement. The keyed digits are made once, not for each character."""
    return let(_stream(key, kind, form, attempt), lambda stream: _made(kind, form, hint, stream, attempt))


def _made(kind: Column, form: Column, hint: Column, stream: Column, attempt: int) -> Column:
    """The room grows with the attempt: names by a syllable each time, other types, whose formats rarely run out, by a character each time after ROOMY."""
    more = max(0, attempt - ROOMY)
    long = F.concat(form, F.lit("0" * more))
    digits = _shaped(long, stream, F.lit(False))
    head = F.substring(form, 1, 1)
    card = let(digits, lambda d: let(F.concat(head, F.substr(d, F.lit(2), F.char_length(d) - 2)), lambda b: F.when(
        F.pmod(luhn_sum(form), F.lit(10)) == 0, F.concat(b, F.pmod(10 - luhn_sum(F.concat(b, F.lit("0"))), F.lit(10)).cast("string"))).otherwise(F.concat(b, F.substr(d, F.char_length(d), F.lit(1))))))
    octet = lambda at: F.pmod(F.conv(F.substring(stream, at, 4), 16, 10).cast("int"), F.lit(1000 if more else 256)).cast("string")
    ip = F.concat_ws(".", (240 + F.pmod(F.conv(F.substring(stream, 1, 2), 16, 10).cast("int"), F.lit(15))).cast("string"), octet(5), octet(9), octet(13))
    at = F.instr(form, "@")
    local = F.substr(form, F.lit(1), at - 1)
    tld = F.element_at(F.array(F.lit("com"), F.lit("net"), F.lit("org")), F.pmod(F.conv(F.substring(stream, 121, 2), 16, 10).cast("int"), F.lit(3)) + 1)
    email = F.concat(_shaped(F.concat(local, F.lit("0" * more)), stream, F.lit(False)), F.lit("@"), F.substring(stream, 101, 8), F.lit(".example."), tld)
    script = F.when(form.rlike(r"\p{IsCyrillic}"), F.lit("cyrillic")).when(form.rlike(r"\p{IsGreek}"), F.lit("greek")).otherwise(F.lit("latin"))
    # hint: gender, and whether the word is a given name; the first attempts take common given names, later ones make some up
    gender, name = F.substring(hint, 1, 1), F.lit(None).cast("string")
    for s in SYLLABLES:
        made = F.initcap(F.concat(*[_pick(stream, p, SYLLABLES[s]) for p in range(5, min(5 + 4 * (3 + attempt), 126), 4)]))
        ends = lambda some: F.when(gender == "f", some["f"]).when(gender == "m", some["m"]).otherwise(some["n"])  # noqa: E731, B023
        common = F.when(gender == "f", _pick(stream, 1, GIVEN[s, "f"])).when(gender == "m", _pick(stream, 1, GIVEN[s, "m"])).otherwise(_pick(stream, 1, GIVEN[s, "f"] + GIVEN[s, "m"]))
        given = common if attempt < 2 else F.concat(made, ends(ENDINGS[s]))
        name = F.when(script == s, F.when(F.substring(hint, 2, 1) == "g", given).otherwise(F.concat(made, ends(FAMILY_ENDINGS[s])))).otherwise(name)
    is_hex = form.rlike("^[0-9a-fA-F]+$") & form.rlike("[0-9]")
    secret = F.when(form.startswith("AKIA"), F.concat(F.lit("AKIA"), _shaped(F.substr(long, F.lit(5), F.char_length(long)), stream, F.lit(False)))).otherwise(_shaped(long, stream, is_hex))
    # a country's IBAN and a phone's digits keep their first characters: the type and the length stay
    plain = F.concat(F.substring(form, 1, 2), _shaped(F.substr(long, F.lit(3), F.char_length(long)), stream, F.lit(False)))
    # valid check digits where there were
    iban = let(plain, lambda i: F.when(iban_rest(form) == 1, F.concat(F.substring(i, 1, 2), F.lpad((98 - iban_rest(F.concat(F.substring(i, 1, 2), F.lit("00"), F.substr(i, F.lit(5), F.char_length(i))))).cast("string"), 2, "0"), F.substr(i, F.lit(5), F.char_length(i)))).otherwise(i))
    return (F.when(kind == "account", card).when(kind == "ip", ip).when(kind == "email", email).when(kind == "name", name)
            .when(kind == "iban", iban).when(kind == "secret", secret).otherwise(digits))


def _written(kind: Column, mention: Column, new: Column) -> Column:
    """The surrogate in the mention's own format: its digits dealt to the mention's digits, those of a longer one at the end."""
    def deal(s: Column, c: Column) -> Column:
        digit = c.rlike(r"\d") | ((kind == "iban") & c.rlike("[A-Z]"))
        return F.struct(F.concat(s["out"], F.when(digit, F.substr(new, s["n"] + 1, F.lit(1))).otherwise(c)).alias("out"), (s["n"] + F.when(digit, 1).otherwise(0)).alias("n"))

    dealt = F.aggregate(F.split(_national(kind, mention), ""), F.struct(F.lit("").alias("out"), F.lit(0).alias("n")), deal, lambda s: F.concat(s["out"], F.substr(new, s["n"] + 1, F.char_length(new))))
    return (F.when(kind == "phone", F.concat(_country(mention), dealt)).when(kind.isin("account", "ssn", "iban"), dealt)
            .when((kind == "name") & (mention == F.upper(mention)), F.upper(new)).otherwise(new))


def _gender(text: Column) -> Column:
    """The words of titled names, in canonical form: the gender of the title, and whether the word is a given name (not the last one)."""
    def words(t: Column) -> Column:
        gender = F.when(t.rlike(rf"^(?:{_any_case(FEMALE)})\b"), "f").when(t.rlike(rf"^(?:{_any_case(MALE)})\b"), "m").otherwise("n")
        return let(F.regexp_extract_all(_untitled(t), F.lit(NAME_WORD), F.lit(0)), lambda w: F.transform(w, lambda x, i: F.struct(
            canonical(F.lit("name"), x).alias("name"), gender.alias("gender"), (i < F.size(w) - 1).alias("given"))))

    return F.flatten(F.transform(_titled_names(text), words))


def entities(docs: DataFrame, key: str, text: str = "text") -> DataFrame:
    """kind, form, surrogate: the distinct entities of the corpus and their distinct replacements."""
    return _entities(cut_texts(docs, text), key)


def _entities(cut: DataFrame, key: str) -> DataFrame:
    found = cut.select(F.explode("__m").alias("m")).distinct()
    found = found.select(kind_of(F.col("m")).alias("kind"), "m").select("kind", F.explode(parts_of(F.col("m"), F.col("kind"))).alias("x"))
    found = found.select("kind", canonical(F.col("kind"), F.col("x.part")).alias("form")).distinct()
    hints = cut.select(F.explode("__g").alias("g")).groupBy(F.col("g.name").alias("form"))
    # a word that titles of both genders precede is neither; one that ever stands before another is a given name
    sole = lambda x: F.bool_or(F.col("g.gender") == x)
    hints = hints.agg(F.concat(F.when(sole("f") & ~sole("m"), "f").when(sole("m") & ~sole("f"), "m").otherwise("n"), F.when(F.bool_or("g.given"), "g").otherwise("f")).alias("hint"))
    pending = persisted(found.join(hints, "form", "left").select("kind", "form", F.when(F.col("kind") == "name", F.coalesce("hint", F.lit("nf"))).otherwise("nf").alias("hint")))
    every = pending.select("kind", F.col("form").alias("surrogate"))
    settled = None
    for attempt in count():  # ends: each attempt has more room than the last
        tried = pending.withColumn("surrogate", _surrogate(F.col("kind"), F.col("form"), F.col("hint"), key, attempt))
        first = F.row_number().over(Window.partitionBy("kind", "surrogate").orderBy("form")) == 1
        taken = every.withColumn("taken", F.lit(True)) if settled is None else every.union(settled.select("kind", "surrogate")).distinct().withColumn("taken", F.lit(True))
        tried = persisted(tried.withColumn("first", first).join(taken, ["kind", "surrogate"], "left").withColumn("ok", F.col("first") & F.col("taken").isNull()))
        won = tried.where("ok").select("kind", "form", "surrogate")
        settled = won if settled is None else settled.union(won)
        pending = tried.where(~F.col("ok")).select("kind", "form", "hint")
        if pending.isEmpty():
            return settled


def replace(docs: DataFrame, key: str, text: str = "text") -> DataFrame:
    """docs with the text rewritten; n_entities is added."""
    others = [c for c in docs.columns if c not in (text, "n_entities")]
    cut = cut_texts(docs, text, *others)
    table = _entities(cut, key)
    each = cut.select(F.col("__m").alias("old")).distinct().select("old", F.posexplode("old").alias("at", "m"))
    each = each.select("old", "at", kind_of(F.col("m")).alias("kind"), "m").select("old", "at", "kind", F.posexplode(parts_of(F.col("m"), F.col("kind"))).alias("j", "x"))
    each = each.withColumn("form", canonical(F.col("kind"), F.col("x.part")))
    new = each.join(table, ["kind", "form"]).select("old", F.struct("at", "j", F.concat("x.before", _written(F.col("kind"), F.col("x.part"), F.col("surrogate")), "x.after").alias("new")).alias("x"))
    lists_ = new.groupBy("old").agg(F.array_sort(F.collect_list("x")).alias("x"))
    whole = F.transform(F.sequence(F.lit(0), F.size("old") - 1), lambda i: F.array_join(F.transform(F.filter("x", lambda p: p["at"] == i), lambda p: p["new"]), ""))
    swaps = persisted(lists_.select(F.col("old").alias("__old"), whole.alias("__new")))
    # lists that many texts share would meet in one task: not where all distinct lists fit a broadcast
    size = swaps.agg(F.sum(F.octet_length(F.array_join("__old", "")) + F.octet_length(F.array_join("__new", "")) + 64 * F.size("__old"))).first()[0]
    swaps = F.broadcast(swaps) if (size or 0) <= BROADCAST_BYTES else swaps
    plain = docs.where(~has_mention(F.col(text))).select(*others, text, F.lit(0).cast("long").alias("n_entities"))
    hit = cut.join(swaps, F.col("__m") == F.col("__old"))
    rewritten = F.array_join(F.transform("__rest", lambda part, i: F.concat(part, F.coalesce(F.get(F.col("__new"), i), F.lit("")))), "")
    hit = hit.select(*others, rewritten.alias(text), F.size("__m").cast("long").alias("n_entities"))
    return plain.unionByName(hit)
