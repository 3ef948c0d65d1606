"""Personal data replaced by surrogates, with DataFrame functions only.

Entities: e-mail addresses, access keys, passwords, quoted hexadecimal secrets, IPv4 addresses, payment card numbers,
international telephone numbers, US social security numbers, IBANs, and names: after a title, and wherever a document
names a person again that it has named with a title, by full name, surname or first name.

A mention is reduced to what it names: an address in lower case and its domain, a number without blanks and dashes, a
surname, a first name. For each of these a surrogate is drawn by a keyed hash (HMAC-SHA256) of its kind and value, with
its type, script and length, and for a first name with the gender of the titles it follows; a card number that passes the
Luhn test gives one that passes it. The layout of each mention (title, capitals, blanks, dashes) is put on afterwards, so
the same entity gets the same surrogate everywhere, however it is written. Distinct entities get distinct surrogates, and
none that is itself an entity of the corpus: clashes are found by an aggregate over all candidates, and every entity but
the first of a clash draws again, in the same form.

A first pass finds the entities and writes the documents once; those without any are not touched again. For the others
only positions and surrogates are shuffled, never texts of documents without entities.
"""

from __future__ import annotations

import hashlib
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import join_counted, materialize, release

# What is detected, in order of precedence; parts of surrogate names by script and gender.
OCTET = r"(?:25[0-5]|2[0-4]\d|1\d\d|[1-9]?\d)"
TITLES = {"m": ["Mr", "Herr", "Señor", "Monsieur", "Г-н"], "f": ["Mrs", "Ms", "Miss", "Frau", "Señora", "Señorita", "Madame", "Mme", "Г-жа"], "n": ["Dr", "Prof"]}
TITLE = r"(?:" + "|".join(t for own in TITLES.values() for t in own) + r")\.? "
TOKEN = r"\p{Lu}\p{L}*+(?:['-](?!s(?!\p{L}))\p{L}++)*+"
FORMS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]*+@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+",
    "access_key": r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])",
    "password": r"(?<![A-Za-z0-9])(?i:password|passwd|pwd)[=:][^\s\"',;]++",
    "hex_secret": r"(?<=\")[0-9a-f]{32,64}(?=\")",
    "ipv4": rf"(?<![\d.]){OCTET}(?:\.{OCTET}){{3}}(?![\d]|\.\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "phone": r"(?<![\w+])\+\d{1,3}[ .-]?(?:\(\d{1,4}\)[ .-]?)?\d{2,4}(?:[ .-]?\d{2,4}){1,3}(?!\d)",
    "card": r"(?<![\w.+-])(?:\d{13,19}|\d{4}(?:[ -]\d{4}){3})(?![\w-])",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])",
    "name": rf"(?<![\p{{L}}]){TITLE}{TOKEN}(?: {TOKEN})?",
}
PATTERN = "|".join(FORMS.values())
#: Every entity has one of these; most texts have none.
GUARD = r"[@\d]|(?i:passw(?:or)?d|pwd)[=:]|(?:AKIA|ASIA)[A-Z]{16}|\"[a-f]{32}|" + rf"(?<!\p{{L}}){TITLE}\p{{Lu}}"
#: Lengths of country codes: one digit, two, or else three.
COUNTRY = r"^\+(?:[17]|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3}|)"
HEADS = {
    "latin": ["Al", "Ber", "Cor", "Dan", "El", "Fen", "Gar", "Hol", "Ing", "Jan", "Kel", "Lor", "Mar", "Nor", "Ols", "Per", "Quin", "Ros", "Sten", "Tor", "Ul", "Ver", "Wal", "Zel"],
    "cyrillic": ["Ан", "Бор", "Вал", "Гал", "Дан", "Ель", "Жан", "Зин", "Кор", "Лен", "Мар", "Ник", "Ольг", "Пав", "Рус", "Тим"],
}
MIDDLES = {"latin": ["a", "e", "i", "o", "en", "er", "in", "or"], "cyrillic": ["а", "е", "и", "о", "ен", "ер", "ин", "ов"]}
TAILS = {
    ("latin", "last"): ["berg", "dorf", "feld", "gren", "holm", "lund", "mann", "quist", "sen", "stein", "strand", "ton", "vik", "wald", "wood", "ley"],
    ("latin", "m"): ["bert", "do", "mir", "rik", "nus", "win", "thor", "vin"],
    ("latin", "f"): ["lia", "na", "ra", "tta", "dis", "belle", "line", "thea"],
    ("latin", "n"): ["li", "mie", "ny", "sy", "lee", "vy", "ry", "ke"],
    ("cyrillic", "last"): ["ленко", "ченко", "щук", "дюк", "бенко", "рчук", "ненко", "венко"],
    ("cyrillic", "m"): ["слав", "мир", "лий", "рий", "тан", "дан", "лей", "ген"],
    ("cyrillic", "f"): ["на", "лия", "рина", "слава", "та", "жена", "вера", "сия"],
    ("cyrillic", "n"): ["ша", "ня", "ля", "ка", "ся", "тя", "ря", "жа"],
}
DOMAINS = ["example.com", "example.net", "example.org"]
UPPER, LOWER, DIGITS, HEX = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789", "0123456789abcdef"
NAMED = ("name", "full", "last", "first")


def entities(text: Column) -> Column:
    return F.when(text.rlike(GUARD), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).otherwise(F.array().cast("array<string>"))


def entity_type(value: Column) -> Column:
    out = None
    for name, form in FORMS.items():
        form = form.replace(r'(?<=\")', "").replace(r'(?=\")', "")
        fits = value.rlike(f"^(?:{form})$")
        out = F.when(fits, name) if out is None else out.when(fits, name)
    return out.otherwise("other")


def keyed_hash(text: Column, key: str) -> Column:
    """HMAC-SHA256 of a string under a key, as 64 hexadecimal digits."""
    raw = key.encode()
    raw = (hashlib.sha256(raw).digest() if len(raw) > 64 else raw).ljust(64, b"\0")
    inner, outer = (F.lit(bytes(b ^ x for b in raw)) for x in (0x36, 0x5C))
    return F.sha2(F.concat(outer, F.unhex(F.sha2(F.concat(inner, text.cast("binary")), 256))), 256)


def _draw(seed: Column, at: Column, size: int) -> Column:
    """A number below size from three digits of a 128-digit keyed hash, for place `at`."""
    return (F.conv(F.substring(seed, F.pmod(at * 3, F.lit(126)) + 1, F.lit(3)), 16, 10).cast("int") % size).cast("int")


def _one(seed: Column, at: Column, letters: str) -> Column:
    return F.substring(F.lit(letters), _draw(seed, at, len(letters)) + 1, F.lit(1))


def _pick(seed: Column, at: Column, own: list[str]) -> Column:
    return F.element_at(F.array(*map(F.lit, own)), _draw(seed, at, len(own)) + 1)


def _more(attempt: Column, from_: int, one) -> Column:
    """one(k) for each attempt from the given one on, joined; nothing before."""
    return F.when(attempt >= from_, F.array_join(F.transform(F.sequence(F.lit(from_), F.greatest(attempt, F.lit(from_))), one), "")).otherwise(F.lit(""))


def _scramble(value: Column, seed: Column, kept: Column | int = 0, hexes: bool = False) -> Column:
    """Every ASCII letter and digit from place `kept` on replaced by one of its kind; everything else stays."""

    def letter(c: Column, i: Column) -> Column:
        if hexes:
            swap = _one(seed, i, HEX)
        else:
            swap = F.when(c.rlike("[0-9]"), _one(seed, i, DIGITS)).when(c.rlike("[A-Z]"), _one(seed, i, UPPER)).when(c.rlike("[a-z]"), _one(seed, i, LOWER)).otherwise(c)
        return F.when(i < kept, c).otherwise(swap)

    return F.array_join(F.transform(F.split(value, ""), letter), "")


def _luhn_sum(digits: Column) -> Column:
    """Luhn sum of a string of digits, the last one counting once."""
    d = F.transform(F.split(F.reverse(digits), ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0)))
    return F.aggregate(d, F.lit(0), lambda a, x: a + x)


def _card(value: Column, seed: Column) -> Column:
    """Digits of a card: the first stays, and the last makes the Luhn sum what it was if that passed."""
    swapped = F.transform(F.array(_scramble(value, seed, 1)), lambda s: F.concat(F.substring(s, F.lit(1), F.length(s) - 1), ((10 - _luhn_sum(F.concat(F.substring(s, F.lit(1), F.length(s) - 1), F.lit("0"))) % 10) % 10).cast("string")))[0]
    return F.when(_luhn_sum(value) % 10 == 0, swapped).otherwise(_scramble(value, seed, 1))


def _name_part(kind: Column, value: Column, gender: Column, attempt: Column, seed: Column) -> Column:
    """A surname or first name from a head, middles and a tail; each further attempt has one middle more."""
    script = F.when(value.rlike(r"\p{IsCyrillic}"), "cyrillic").otherwise("latin")
    role = F.when(kind == "last", "last").otherwise(F.coalesce(gender, F.lit("n")))
    by = lambda lists, key, at: F.coalesce(*[F.when(key == k, _pick(seed, at, own)) for k, own in lists.items()])
    tails = {f"{s}/{r}": own for (s, r), own in TAILS.items()}
    return F.concat(by(HEADS, script, F.lit(0)), by(MIDDLES, script, F.lit(1)), _more(attempt, 1, lambda k: by(MIDDLES, script, k + 2)), by(tails, F.concat_ws("/", script, role), F.lit(2)))


def surrogate(kind: Column, value: Column, gender: Column, attempt: Column, seed: Column) -> Column:
    """The candidate of an entity for one attempt, in the entity's reduced form; forms of open length grow with later attempts."""
    local = F.substring_index(value, "@", 1)
    letters = lambda at: _one(seed, at + 20, LOWER)
    cut = F.length(F.regexp_extract(value, r"^\w+[=:]", 0))
    octets = [_draw(seed, F.lit(k), 256).cast("string") for k in (1, 2, 3)]
    label = F.array_join(F.transform(F.sequence(F.lit(1), F.greatest(F.length(F.substring_index(value, ".", 1)), F.lit(6))), lambda k: _one(seed, k, LOWER)), "")
    return (
        F.when(kind == "email", F.concat(_scramble(local, seed), _more(attempt, 3, letters), F.lit("@"), F.substring_index(value, "@", -1)))
        .when(kind == "domain", F.concat(label, _more(attempt, 3, letters), F.lit("."), _pick(seed, F.lit(0), DOMAINS)))
        .when(kind == "access_key", _scramble(value, seed, 4))
        .when(kind == "password", F.concat(_scramble(value, seed, cut), _more(attempt, 3, letters)))
        .when(kind == "hex_secret", _scramble(value, seed, hexes=True))
        # private addresses, then the range that is reserved and assigned to nobody
        .when(kind == "ipv4", F.concat_ws(".", F.when(attempt < 3, F.lit("10")).otherwise((_draw(seed, F.lit(0), 15) + 240).cast("string")), *octets))
        .when(kind == "phone", _scramble(value, seed, F.length(F.regexp_extract(value, COUNTRY, 0))))
        .when(kind == "card", _card(value, seed))
        .when(kind == "iban", _scramble(value, seed, 2))
        .when(kind.isin("last", "first"), _name_part(kind, value, gender, attempt, seed))
        .otherwise(_scramble(value, seed))
    )


def surrogates(known: DataFrame, key: str, max_rounds: int = 64) -> DataFrame:
    """known (kind, value, gender, n; one row for each kind and value) with surrogate: all distinct, none a value.

    A pool that is too small for its entities (more IPv4 addresses than unassigned ones, say) ends in an error.
    """
    tasks = known.sparkSession.sparkContext.defaultParallelism

    def drawn(df: DataFrame) -> DataFrame:
        text = lambda end: F.concat_ws("|", "kind", "value", F.col("attempt").cast("string"), F.lit(end))
        seeded = df.withColumn("seed", F.concat(keyed_hash(text(""), key), keyed_hash(text("+"), key)))
        return seeded.withColumn("surrogate", surrogate(*map(F.col, ("kind", "value", "gender", "attempt", "seed")))).drop("seed")

    table = materialize(drawn(known.repartition(tasks, "kind", "value").withColumn("attempt", F.lit(0))), "surrogates")
    for _ in range(max_rounds):
        first = table.groupBy("surrogate").agg(F.min(F.struct((-F.col("attempt")).alias("a"), F.col("kind"), F.col("value"))).alias("own"), F.count("*").alias("n"))
        real = table.select(F.col("value").alias("surrogate"), F.lit(True).alias("real")).distinct()
        clash = first.join(real, "surrogate", "left").where("n > 1 or real").select("surrogate", F.col("own.kind").alias("owner_kind"), F.col("own.value").alias("owner"), F.coalesce("real", F.lit(False)).alias("real"))
        again = table.join(clash, "surrogate").where("real or value <> owner or kind <> owner_kind").select("kind", "value", "gender", "n", (F.col("attempt") + 1).alias("attempt"))
        again = materialize(drawn(again), "again")
        if not again.limit(1).count():
            return table.select("kind", "value", "surrogate", "n")
        old, table = table, materialize(table.join(again.select("kind", "value"), ["kind", "value"], "left_anti").unionByName(again), "surrogates")
        release(old, again)
    raise RuntimeError(f"surrogates still clash after {max_rounds} rounds")


def _bare(value: Column) -> Column:
    return F.regexp_replace(value, f"^{TITLE}", "")


def _woven(value: Column, made: Column) -> Column:
    """Letters and digits of value replaced one by one by those of made; everything else stays."""
    nth = lambda i: F.length(F.regexp_replace(F.substring(value, F.lit(1), i + 1), "[^0-9A-Za-z]", ""))
    bare = F.regexp_replace(made, "[^0-9A-Za-z]", "")
    return F.array_join(F.transform(F.split(value, ""), lambda c, i: F.when(c.rlike("[0-9A-Za-z]"), F.substring(bare, nth(i), F.lit(1))).otherwise(c)), "")


def _cased(value: Column, made: Column) -> Column:
    """made with capitals where value has them; it may be longer."""
    letter = lambda c, i: F.when(c.rlike("[A-Z]"), F.upper(F.substring(made, i + 1, F.lit(1)))).otherwise(F.substring(made, i + 1, F.lit(1)))
    return F.concat(F.array_join(F.transform(F.split(value, ""), letter), ""), F.substring(made, F.length(value) + 1, F.length(made)))


def replacements(found: DataFrame, key: str) -> DataFrame:
    """(hint, value, n, made) for each distinct mention of found (hint, value).

    hint: how a document uses a bare name (full, last or first), empty for all other mentions. n: how often it stands.
    """
    mentions = found.groupBy("hint", "value").agg(F.count("*").alias("n"))
    mentions = mentions.withColumn("kind", F.when(F.col("hint") != "", F.col("hint")).otherwise(entity_type(F.col("value"))))
    tokens = F.split(_bare(F.col("value")), " ")
    title = F.regexp_extract("value", r"^(\S+?)\.? ", 1)
    gender = F.when(F.col("kind") != "name", None).when(title.isin(TITLES["m"]), "m").when(title.isin(TITLES["f"]), "f")
    kind = F.col("kind")
    mentions = mentions.withColumns(
        {
            "last": F.when(kind.isin("name", "full", "last"), F.element_at(tokens, -1)),
            "first": F.when(kind == "first", F.col("value")).when(kind.isin("name", "full") & (F.size(tokens) > 1), tokens[0]),
            "gender": gender,
            "domain": F.when(kind == "email", F.lower(F.substring_index("value", "@", -1))),
            "own": F.when(kind == "email", F.lower("value")).when(kind.isin("phone", "card", "ssn", "iban"), F.regexp_replace("value", "[^0-9A-Za-z+]", "")).when(~kind.isin(*NAMED), F.col("value")),
        }
    )
    mentions = materialize(mentions, "mentions")
    part = lambda k, v, g=None: F.struct(F.lit(k).alias("kind") if isinstance(k, str) else k.alias("kind"), F.col(v).alias("value"), (F.col(g) if g else F.lit(None).cast("string")).alias("gender"))
    parts = mentions.select(F.explode(F.array(part("last", "last"), part("first", "first", "gender"), part("domain", "domain"), part(kind, "own"))).alias("p")).select("p.*").where("value is not null")
    by = lambda g: F.count_if(F.col("gender") == g)
    known = parts.groupBy("kind", "value").agg(F.count("*").alias("n"), F.when((by("m") >= by("f")) & (by("m") > 0), "m").when(by("f") > 0, "f").otherwise("n").alias("gender"))
    drawn = materialize(surrogates(materialize(known, "known"), key), "drawn")

    def look_up(rows: DataFrame, of: str, on: str, out: str) -> DataFrame:
        return join_counted(rows, drawn.where(F.col("kind") == of).select(F.col("value").alias(on), F.col("surrogate").alias(out), F.col("n").alias("__n")), on, "__n")

    mails = look_up(look_up(mentions.where(kind == "email"), "domain", "domain", "site"), "email", "own", "to")
    mails = mails.withColumn("made", F.concat(_cased(F.substring_index("value", "@", 1), F.substring_index("to", "@", 1)), F.lit("@"), F.col("site")))
    surnames = look_up(mentions.where("last is not null and first is null"), "last", "last", "l").withColumn("f", F.lit(None).cast("string"))
    whole = look_up(look_up(mentions.where("last is not null and first is not null"), "last", "last", "l"), "first", "first", "f")
    given = look_up(mentions.where("last is null and first is not null"), "first", "first", "f").withColumn("l", F.lit(None).cast("string"))
    people = surnames.unionByName(whole).unionByName(given)
    people = people.withColumn("made", F.concat(F.regexp_extract("value", f"^{TITLE}", 0), F.concat_ws(" ", "f", "l")))
    rest = mentions.where(~kind.isin("email", *NAMED)).select("hint", "value", "n", "kind", "own")
    others = drawn.where(~F.col("kind").isin("email", "domain", "last", "first")).select(F.col("kind"), F.col("value").alias("own"), "surrogate")
    rest = rest.join(others, ["kind", "own"])
    rest = rest.withColumn("made", F.when(F.col("kind").isin("phone", "card", "ssn", "iban"), _woven(F.col("value"), F.col("surrogate"))).otherwise(F.col("surrogate")))
    return reduce(DataFrame.unionByName, [df.select("hint", "value", "n", "made") for df in (mails, people, rest)])


def _free_name(wanted: str, taken: list[str]) -> str:
    k, name = 2, wanted
    while name.lower() in {t.lower() for t in taken}:
        name, k = f"{wanted}_{k}", k + 1
    return name


def replace_entities(docs: DataFrame, key: str, text_col: str = "text", count_col: str = "n_entities") -> DataFrame:
    """docs with every entity in the text replaced, and n_entities, the number of replaced places.

    key: the secret of the keyed hash; whoever has it can test guesses. All columns of docs stay, whatever their names; if
    one is called as the count, the count gets the next free name (n_entities_2). A null text stays null with no entities,
    and an empty one empty. Every row is treated by itself, so rows that repeat an id, or have none, are alike. Work that
    is done for one row at once grows with the entities of its text. An empty table gives no rows.
    """
    if not key:
        raise ValueError("a key is needed")
    names = docs.columns
    count_col = _free_name(count_col, names)
    at = next(k for k, n in enumerate(names) if n.lower() == text_col.lower())
    plain = [f"c{k}" for k in range(len(names))]
    text = F.col(plain[at]).cast("string")
    rows = docs.toDF(*plain).withColumn("rid", F.monotonically_increasing_id()).withColumn("ents", entities(text))
    titled = F.filter("ents", lambda e: e.rlike(f"^{TITLE}"))
    rows = rows.withColumn("people", F.array_distinct(F.transform(titled, _bare)))
    rows = rows.withColumn("full", F.filter("people", lambda p: p.contains(" ")))
    rows = rows.withColumn("last", F.array_distinct(F.transform("people", lambda p: F.substring_index(p, " ", -1)))).withColumn("first", F.array_distinct(F.transform("full", lambda p: F.substring_index(p, " ", 1))))
    again = F.concat(F.lit(PATTERN + r"|(?<![\p{L}\p{N}])(?:"), F.array_join(F.concat("full", "last", "first"), "|"), F.lit(r")(?![\p{L}\p{N}-])"))
    rows = rows.withColumn("pattern", F.when(F.size("people") > 0, again))
    all_ = F.when(F.col("pattern").isNotNull(), F.regexp_extract_all(text, F.col("pattern"), F.lit(0))).otherwise(F.col("ents"))
    hint = lambda e: F.when(F.array_contains("full", e), "full").when(F.array_contains("last", e), "last").when(F.array_contains("first", e), "first").otherwise("")
    rows = rows.withColumn("ents", F.transform(all_, lambda e: F.struct(hint(e).alias("hint"), e.alias("value"))))
    rows = materialize(rows.select(*plain, "rid", "ents", "pattern", (F.size("ents") > 0).alias("has")), "marked", "zstd")
    spots = materialize(rows.where("has").select("rid", F.posexplode("ents").alias("pos", "e")).select("rid", "pos", "e.hint", "e.value"), "spots")
    made = materialize(replacements(spots, key).withColumn("mention", F.concat_ws("|", "hint", "value")).select("mention", "made", "n"), "made")
    placed = join_counted(spots.select("rid", "pos", F.concat_ws("|", "hint", "value").alias("mention")), made, "mention", "n")
    gathered = placed.groupBy("rid").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "made"))), lambda x: x["made"]).alias("made"))
    gaps = F.when(F.col("pattern").isNull(), F.split(text, PATTERN, -1)).otherwise(F.split(text, F.col("pattern"), -1))
    woven = F.array_join(F.flatten(F.transform(F.arrays_zip(gaps.alias("g"), F.col("made").alias("e")), lambda z: F.array(F.coalesce(z["g"], F.lit("")), F.coalesce(z["e"], F.lit(""))))), "")
    changed = rows.where("has").join(gathered, "rid").withColumn(plain[at], woven).withColumn("count", F.size("ents").cast("long"))
    same = rows.where("not has").withColumn("count", F.lit(0).cast("long"))
    out = changed.select(*plain, "count").unionByName(same.withColumn(plain[at], text).select(*plain, "count"))
    return out.toDF(*names, count_col)
