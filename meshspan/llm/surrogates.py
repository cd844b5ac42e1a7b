"""Personal data: keyed, type-consistent surrogates, in DataFrame functions alone.

One pattern finds e-mail addresses, account and card numbers, telephone and social security numbers,
bank accounts, network addresses, secrets and titled names. An entity is its canonical form (case,
separators, titles, country and trunk codes removed), so that its spellings share one surrogate, in every document;
a name of several words that a text first gives with a title is replaced there without it too. A surrogate is drawn
from SHA-256 of the key, the type and the canonical form; it keeps the format: digits stay digits,
letters stay letters of the same case and script, separators, country codes, top-level domains, private networks,
card checksums and the check digits of bank accounts stay valid; a person's gender is that of all titles the corpus
gives the name. All surrogates of the corpus are checked, hosts of addresses for themselves: an entity whose
surrogate another has, or which is itself an entity of the corpus, draws again until all are distinct.

Every repetition in a pattern is possessive, bounded, or of single characters, so that no stack grows with a text.
The pattern runs once over each document; only documents with entities are shuffled. Entities are reduced to distinct ones before they are joined,
and joined back from a stored table, so that an entity in a third of all documents can be split.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from meshspan.llm.common import stored

_TITLES = {"m": "Mr|Herr|Señor|Sr|Don", "f": "Mrs|Ms|Miss|Mme|Mlle|Frau|Señora|Sra|Doña", "n": "Dr|Prof"}
_ANY_TITLE = "|".join(_TITLES.values())
#: Titles in a row, before a name.
_TITLED = rf"(?:(?:{_ANY_TITLE})\.? ){{1,4}}"
# Small words inside names.
_PARTICLES = "van|von|de|del|della|di|da|dos|du"
_PARTICLE_AFTER = "der|den|la|las|los|le"
#: A word of a name: capitals, letters and digits with apostrophes and hyphens inside, or initials. A
#: possessive ending stays outside. Possessive quantifiers: no stack grows with the text.
_NAME_WORD = r"(?:(?:\p{Lu}\.[ -]?(?=\p{Lu}))*+\p{Lu}(?:[\p{L}\p{M}\p{N}]|['’](?!s(?![\p{L}\p{N}]))(?=\p{L})|[-‐‑](?=\p{L}))*+(?:(?<=[\p{Z}.‐‑-]\p{Lu})\.)?+)"
_PARTICLE = rf"(?:(?:{_PARTICLES}) (?:(?:{_PARTICLE_AFTER}) )?+)"
_OCTET = r"(?:25[0-5]|2[0-4]\d|1?\d?\d)"
#: Patterns by type, in the order in which they are tried at a place.
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@[\p{L}\p{N}-]+(?:\.[\p{L}\p{N}-]+){0,126}\.\p{L}{2,24}",  # a name has at most 127 labels
    "iban": r"(?<![\p{L}\p{N}])[A-Z]{2}\d{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?(?![\p{L}\p{N}])",
    "secret": r"(?<![\p{L}\p{N}])(?:(?=[0-9A-Fa-f]*\d)(?:[0-9a-f]{32,}|[0-9A-F]{32,})|(?:AKIA|ASIA)[0-9A-Z]{16}|(?:gh[po]_|sk-|xox[bp]-)[A-Za-z0-9_-]{16,})(?![\p{L}\p{N}])",
    "card": r"(?<![\p{L}\p{N}.+-])\d(?:[ -]?\d){12,18}(?![\p{L}\p{N}])",
    "phone": r"(?:(?:\+\d{1,3}[ .-]?)?\(\d{2,4}\)[ .-]?\d{3,4}[ .-]?\d{3,4}|(?<!\d)\+\d{1,3}(?:[ .-]?\d)?(?:[ .-]?\d{2,4}){2,5}|(?<![\p{L}\p{N}.-])\d{3}[-. ]\d{3}[-. ]\d{4}|(?<![\p{L}\p{N}.-])0\d(?:[ .-]\d{2}){4}|(?<![\p{L}\p{N}.-])0\d{2,4}[ -]\d{3,4}[ -]\d{3,4})(?!\d)",
    "ssn": r"(?<![\p{L}\p{N}-])\d{3}-\d{2}-\d{4}(?![\p{L}\p{N}-])",
    "hex_address": r"(?<![\p{L}\p{N}:])(?:(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}|(?:[0-9A-Fa-f]{2}[:-]){5}[0-9A-Fa-f]{2})(?![\p{L}\p{N}:])",
    "ip": rf"(?<![\p{{L}}\p{{N}}.])(?:{_OCTET}\.){{3}}{_OCTET}(?![\p{{L}}\p{{N}}]|\.\d)",
    "name": rf"(?<![\p{{L}}\p{{N}}])(?=[MHSDFP]){_TITLED}{_PARTICLE}?{_NAME_WORD}(?: {_PARTICLE}?(?!(?:{_ANY_TITLE})\.? \p{{Lu}}){_NAME_WORD})*+(?![\p{{L}}\p{{M}}\p{{N}}])",
}
ENTITY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Documents that this does not match hold no entity: each type has an @, two digits in a row, digits parted
#: by a dot, space or hyphen, a colon between hexadecimal digits, three pairs of them with hyphens, 32 of
#: them in a row, the prefix of a key, or a title. Wider than ENTITY, never narrower.
CHEAP = (
    rf"@|\d[\d. -]\d|\d\d|[0-9A-Fa-f]:[0-9A-Fa-f]|(?:[0-9A-Fa-f]{{2}}-){{3}}|[0-9A-Fa-f]{{32}}|AKIA|ASIA|gh[po]_|sk-|xox[bp]-|"
    rf"(?:{_ANY_TITLE})\.? (?:\p{{Lu}}|(?:{_PARTICLES}) )"
)

# Alphabets by script and case, given names by gender, syllables of surnames.
_ALPHABETS = (
    ("[0-9]", "0123456789"),
    ("[a-z]", "abcdefghijklmnopqrstuvwxyz"),
    ("[A-Z]", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
    (r"[\p{IsLatin}&&\p{Ll}]", "àáâäçèéêëìíîïñòóôöùúûü"),
    (r"[\p{IsLatin}&&\p{Lu}]", "ÀÁÂÄÇÈÉÊËÌÍÎÏÑÒÓÔÖÙÚÛÜ"),
    (r"[\p{IsCyrillic}&&\p{Ll}]", "абвгдежзиклмнопрстуфхцчшэюя"),
    (r"[\p{IsCyrillic}&&\p{Lu}]", "АБВГДЕЖЗИКЛМНОПРСТУФХЦЧШЭЮЯ"),
    (r"[\p{IsGreek}&&\p{Ll}]", "αβγδεζηθικλμνξοπρστυφχψω"),
    (r"[\p{IsGreek}&&\p{Lu}]", "ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ"),
)
_GIVEN = {
    ("m", "latin"): "Adam Bruno Carl David Emil Felix Georg Hugo Ivan Jonas Karl Lukas Marco Noel Oscar Paul Rafael Simon Tomas Victor".split(),
    ("f", "latin"): "Alma Beata Clara Diana Elena Freya Greta Helena Irene Julia Karin Laura Maria Nora Olivia Paula Rosa Sofia Teresa Vera".split(),
    ("m", "cyrillic"): "Антон Борис Виктор Глеб Денис Егор Иван Кирилл Леонид Максим Никита Олег Павел Роман Сергей".split(),
    ("f", "cyrillic"): "Алина Вера Галина Дарья Елена Жанна Инна Ксения Лидия Марина Нина Ольга Полина Раиса Софья".split(),
}
_SYLLABLES = {
    "latin": "ba ben bor cal cor dal den dor fal fen gar gel hal hen kar kel lan lor mar mel nor pal per ral ren sal sel tar ten tor val ven vor wel".split(),
    "cyrillic": "ба бел бор вал вер гор дан дор зор кар кол лан лор мал мар нев пал пер ран рен сав сел тар тер вол".split(),
}
_HASHES = 4  # of 32 bytes each; longer entities use them again


def _bound(value: Column, use) -> Column:
    """``use(value)`` with the value computed once, not once for each element that ``use`` goes through."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _hash(key: str, kind: Column, what: Column, attempt: Column) -> Column:
    parts = [F.sha2(F.concat_ws("\x1f", F.lit(key), kind, what, attempt.cast("string"), F.lit(str(i))), 256) for i in range(_HASHES)]
    return F.concat(*parts)


def _byte(hexes: Column, at: Column) -> Column:
    """Two bytes of the hash as an integer, drawn at a place."""
    return F.conv(F.substr(hexes, F.pmod(at, F.lit(_HASHES * 32 - 1)) * 2 + 1, F.lit(4)), 16, 10).cast("int")


def _pick(alphabet: str | list[str], draw: Column) -> Column:
    if isinstance(alphabet, str):
        return F.substr(F.lit(alphabet), F.pmod(draw, F.lit(len(alphabet))) + 1, F.lit(1))
    return F.element_at(F.array(*map(F.lit, alphabet)), F.pmod(draw, F.lit(len(alphabet))) + 1)


def _chars(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def _swap(text: Column, hexes: Column, from_place: int = 0) -> Column:
    """Every letter and digit replaced by one of its alphabet; all else stays."""
    return _bound(hexes, lambda own: _swapped(text, own, from_place))


def _swapped(text: Column, hexes: Column, from_place: int) -> Column:
    def one(c: Column, i: Column) -> Column:
        draw = _byte(hexes, i)
        first, *rest = _ALPHABETS
        out = F.when(c.rlike(first[0]), _pick(first[1], draw))
        for pattern, alphabet in rest:
            out = out.when(c.rlike(pattern), _pick(alphabet, draw))
        return F.when(i < from_place, c).otherwise(out.otherwise(c))

    return F.array_join(F.transform(_chars(text), one), "")


def _hex_swap(text: Column, hexes: Column) -> Column:
    upper = text.rlike("[A-F]")
    swapped = F.array_join(F.transform(_chars(text), lambda c, i: F.when(c.rlike("[:-]"), c).otherwise(_pick("0123456789abcdef", _byte(hexes, i)))), "")
    return F.when(upper, F.upper(swapped)).otherwise(swapped)


def luhn_sum(digits: Column) -> Column:
    """Luhn sum of a string of digits: every second digit from the right doubled, nines cast out."""
    flipped = F.reverse(_chars(digits))
    values = F.transform(flipped, lambda c, i: F.when(i % 2 == 1, F.when(c.cast("int") >= 5, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)).otherwise(c.cast("int")))
    return F.aggregate(values, F.lit(0), lambda a, v: a + v)


def _iban_check(country: Column, rest: Column) -> Column:
    """The two check digits of a bank account: 98 less the remainder mod 97 of what follows them, the
    country and two zeros, letters counting from 10."""
    remainder = F.aggregate(
        _chars(F.concat(rest, country, F.lit("00"))), F.lit(0), lambda a, c: F.when(c.rlike("[0-9]"), (a * 10 + c.cast("int")) % 97).otherwise((a * 100 + F.ascii(c) - 55) % 97)
    )
    return F.lpad((98 - remainder).cast("string"), 2, "0")


def _title_gender(surface: Column) -> Column:
    return F.when(surface.rlike(rf"^(?:{_TITLES['f']})\.? "), "f").when(surface.rlike(rf"^(?:{_TITLES['m']})\.? "), "m").otherwise("n")


#: What stands before a national number: the country's code, and the digit for calls inside the country.
_TRUNK = r"^(?:(?:\+\d{1,3}(?=[ .-]?\()|\+1|\+\d{1,3}(?=[ .-]))[ .-]?)?\(?0?"
#: Second levels under which a country gives names.
_SECOND_LEVEL = r"\.(?:co|com|org|net|gov|gob|gouv|edu|ac|or|ne)\.\p{L}{2}$"


def _kind(surface: Column) -> Column:
    out = F.when(surface.rlike(f"^(?:{PATTERNS['email']})$"), F.lit("email"))
    for name in list(PATTERNS)[1:]:
        out = out.when(surface.rlike(f"^(?:{PATTERNS[name]})$"), F.lit(name))
    return out.otherwise(F.lit("secret"))


def _canonical(kind: Column, surface: Column) -> Column:
    digits = F.regexp_replace(surface, r"\D", "")
    national = F.regexp_replace(F.regexp_replace(surface, _TRUNK, ""), r"\D", "")
    name = F.lower(F.regexp_replace(surface, rf"^{_TITLED}", ""))
    return (
        F.when(kind == "email", F.lower(surface))
        .when(kind.isin("card", "ssn"), digits)
        .when(kind == "phone", national)
        .when(kind == "iban", F.regexp_replace(surface, " ", ""))
        .when(kind == "name", name)
        .otherwise(surface)
    )


def _syllable_name(hexes: Column, script: Column, from_byte: int) -> Column:
    def built(alphabet: list[str]) -> Column:
        return F.initcap(F.concat(*[_pick(alphabet, _byte(hexes, F.lit(from_byte + 2 * i))) for i in range(3)]))

    return F.when(script == "cyrillic", built(_SYLLABLES["cyrillic"])).otherwise(built(_SYLLABLES["latin"]))


def _host_core(canonical: Column, own: Column, attempt: Column) -> Column:
    """The surrogate of an address's domain: other letters under the same top level; four more where short names are
    used up."""
    labels = F.when(canonical.rlike(_SECOND_LEVEL) & (F.size(F.split(canonical, r"\.")) > 2), F.substring_index(canonical, ".", -2)).otherwise(F.substring_index(canonical, ".", -1))
    more = F.when(attempt >= 6, F.concat(*[_pick("abcdefghijklmnopqrstuvwxyz", _byte(own, F.lit(50 + 3 * i))) for i in range(4)])).otherwise("")
    return F.concat(more, _swap(F.substr(canonical, F.lit(1), F.length(canonical) - F.length(labels)), own), labels)


def _core(key: str, kind: Column, canonical: Column, attempt: Column, gender: Column, host_core: Column, own: Column) -> Column:
    """The surrogate of a canonical form, itself in canonical form (names: with capitals). ``host_core``: the
    surrogate of an address's domain; ``own``: the hash to draw from."""
    email = F.concat(_swap(F.substring_index(canonical, "@", 1), own), F.lit("@"), host_core)
    swapped = _swap(canonical, own, 1)
    body = F.substr(swapped, F.lit(1), F.length(swapped) - 1)
    check = F.pmod(-luhn_sum(F.concat(body, F.lit("0"))), F.lit(10)).cast("string")
    card = F.when(F.pmod(luhn_sum(canonical), F.lit(10)) == 0, F.concat(body, check)).otherwise(swapped)
    phone = F.concat(F.pmod(_byte(own, F.lit(90)), F.lit(8)).__add__(2).cast("string"), F.substr(_swap(canonical, own), F.lit(2)))
    ssn = F.concat(F.pmod(_byte(own, F.lit(90)), F.lit(8)).__add__(1).cast("string"), F.substr(_swap(canonical, own), F.lit(2)))
    rest = _swap(F.substr(canonical, F.lit(5)), own)
    country = F.substr(canonical, F.lit(1), F.lit(2))
    iban = F.concat(country, _iban_check(country, rest), rest)
    drawn = [(F.pmod(_byte(own, F.lit(3 * i)), F.lit(223)) + 1).cast("string") for i in range(4)]
    octets = F.split(canonical, r"\.")
    # private and loopback networks stay what they are, until their few forms are used up
    held = F.when(attempt >= 8, 0).when(canonical.rlike(r"^(?:10|127)\."), 1).when(canonical.rlike(r"^192\.168\.|^169\.254\.|^172\.(?:1[6-9]|2\d|3[01])\."), 2).otherwise(0)
    ip = F.concat_ws(".", *[F.when(held > i, octets[i]).otherwise(d) if i < 2 else d for i, d in enumerate(drawn)])
    prefix = F.regexp_extract(canonical, r"^(AKIA|ASIA|gh[po]_|sk-|xox[bp]-)", 1)
    secret = F.when(canonical.rlike("^[0-9a-f:-]+$|^[0-9A-F:-]+$"), _bound(own, lambda h: _hex_swap(canonical, h))).otherwise(
        F.concat(prefix, _bound(own, lambda h: _swap(F.substr(canonical, F.length(prefix) + 1), h)))
    )
    name = canonical
    script = F.when(name.rlike(r"\p{IsCyrillic}"), "cyrillic").otherwise("latin")
    # small words go, initials stay initials, but for the last word, which is a surname as all others but the first
    small = f"^(?:{_PARTICLES}|{_PARTICLE_AFTER})$"
    words = _bound(F.split(name, " "), lambda all_: F.filter(all_, lambda w, i: ~w.rlike(small) | (i == F.size(all_) - 1)))
    first = _hash(key, F.lit("given"), F.element_at(words, 1), attempt)
    sex = F.when(gender == "n", F.when(F.pmod(_byte(first, F.lit(40)), F.lit(2)) == 0, "m").otherwise("f")).otherwise(gender)
    picked = reduce(
        lambda out, g: out.when((sex == g[0]) & (script == g[1]), _pick(_GIVEN[g], _byte(first, F.lit(0)))), _GIVEN, F.when(F.lit(False), F.lit(""))
    )

    def renamed(word: Column, i: Column, n: Column, script: Column) -> Column:
        family = _hash(key, F.lit("surname"), word, attempt)
        initials = word.rlike(r"^(?:\p{L}\.-?)*+(?:\p{L}\.?)?$") & (i < n - 1)
        other = F.when((i == 0) & (n > 1), picked).otherwise(_syllable_name(family, script, 10))
        return F.when(initials, F.upper(_swap(word, family))).otherwise(other)

    person = _bound(F.struct(words.alias("all"), script.alias("script")), lambda b: F.array_join(F.transform(b["all"], lambda w, i: renamed(w, i, F.size(b["all"]), b["script"])), " "))
    return (
        F.when(kind == "email", email).when(kind == "card", card).when(kind == "phone", phone).when(kind == "ssn", ssn)
        .when(kind == "iban", iban).when(kind == "ip", ip).when(kind == "name", person).otherwise(secret)
    )


def _rendered(kind: Column, surface: Column, core: Column) -> Column:
    """A surrogate in the format of one spelling of its entity."""

    def placed(shape: Column, text: Column) -> Column:
        signs = _chars(text)
        return F.array_join(
            F.transform(_chars(shape), lambda c, i: F.when(c.rlike(r"[0-9A-Za-z]"), F.element_at(signs, F.length(F.regexp_replace(F.substr(shape, F.lit(1), i + 1), "[^0-9A-Za-z]", "")))).otherwise(c)), ""
        )

    code = F.regexp_extract(surface, _TRUNK, 0)
    title = F.regexp_extract(surface, rf"^({_TITLED})", 1)
    same_case = F.array_join(F.zip_with(_chars(core), _chars(surface), lambda c, o: F.when(F.coalesce(o, F.lit("")).rlike(r"\p{Lu}"), F.upper(c)).otherwise(F.coalesce(c, F.lit("")))), "")
    return (
        F.when(kind.isin("card", "ssn", "iban"), placed(surface, core))
        .when(kind == "phone", F.concat(code, placed(F.substr(surface, F.length(code) + 1), core)))
        .when(kind == "name", F.concat(title, core))
        .when(kind == "email", same_case)
        .otherwise(core)
    )


def _settled(entities: DataFrame, key: str, max_rounds: int, hosts: bool = False) -> DataFrame:
    """(kind, canonical, core) of ``entities(kind, canonical, gender, host_core)``: drawn until, in each type, all
    differ and none is an entity."""
    current = entities.withColumn("attempt", F.lit(0))
    originals = entities.select(F.col("kind").alias("_kind"), F.lower("canonical").alias("_original")).distinct()
    same = Window.partitionBy("kind", "_folded").orderBy("canonical")
    for _ in range(max_rounds):
        drawn = current.withColumn("own", _hash(key, F.col("kind"), F.col("canonical"), F.col("attempt")))
        core = _host_core(F.col("canonical"), F.col("own"), F.col("attempt")) if hosts else _core(key, *map(F.col, ("kind", "canonical", "attempt", "gender", "host_core", "own")))
        drawn = drawn.withColumn("core", core)
        drawn = drawn.withColumn("_folded", F.lower("core")).withColumn("_nth", F.row_number().over(same))
        drawn = drawn.join(originals, (F.col("kind") == F.col("_kind")) & (F.col("_folded") == F.col("_original")), "left")
        drawn = stored(drawn.select("kind", "canonical", "gender", "host_core", "attempt", "core", ((F.col("_nth") > 1) | F.col("_original").isNotNull()).alias("clash")), "drawn")
        if not drawn.where("clash").limit(1).count():
            return drawn.select("kind", "canonical", "core")
        current = drawn.select("kind", "canonical", "gender", "host_core", (F.col("attempt") + F.col("clash").cast("int")).alias("attempt"))
    raise RuntimeError("surrogates still collide: a type has too few forms for its entities")


def surrogate_table(surfaces: DataFrame, key: str, max_rounds: int = 24) -> DataFrame:
    """(surface, kind, canonical, surrogate) of the distinct ``surfaces(surface)``; surrogates of
    different entities of a type differ, and none is an entity of the table."""
    known = stored(
        surfaces.select("surface", _kind(F.col("surface")).alias("kind")).withColumn("canonical", _canonical(F.col("kind"), F.col("surface"))).distinct(),
        "surfaces",
    )
    # a name is one person's, whatever titles it has: of the gender that its titles tell, if they agree
    sexes = F.collect_set(F.when(F.col("kind") == "name", F.nullif(_title_gender(F.col("surface")), F.lit("n"))))
    entities = known.groupBy("kind", "canonical").agg(sexes.alias("sexes"))
    entities = entities.select("kind", "canonical", F.when(F.size("sexes") == 1, F.col("sexes")[0]).otherwise("n").alias("gender"), F.when(F.col("kind") == "email", F.substring_index("canonical", "@", -1)).alias("host"))
    entities = stored(entities, "entities")
    hosts = entities.where("host is not null").select(F.lit("domain").alias("kind"), F.col("host").alias("canonical"), F.lit("n").alias("gender"), F.lit(None).cast("string").alias("host_core")).distinct()
    hosts = _settled(stored(hosts, "hosts"), key, max_rounds, hosts=True).select(F.col("canonical").alias("host"), F.col("core").alias("host_core"))
    entities = stored(entities.join(hosts, "host", "left").select("kind", "canonical", "gender", "host_core"), "entities")
    joined = known.join(_settled(entities, key, max_rounds), ["kind", "canonical"])
    return stored(joined.select("surface", "kind", "canonical", _rendered(F.col("kind"), F.col("surface"), F.col("core")).alias("surrogate")), "surrogates")


def _bare_names(known: Column) -> Column:
    """Of a map from surfaces to surrogates, the names of several words without their titles, longest first:
    structs of a pattern and what replaces it."""
    pairs = F.filter(F.map_entries(known), lambda e: e["key"].rlike(rf"^{_TITLED}"))
    bare = F.transform(pairs, lambda e: F.struct(F.regexp_replace(e["key"], rf"^{_TITLED}", "").alias("name"), F.regexp_replace(e["value"], rf"^{_TITLED}", "").alias("new")))
    several = F.filter(F.array_distinct(bare), lambda e: e["name"].contains(" "))
    order = F.array_sort(F.transform(several, lambda e: F.struct((-F.length(e["name"])).alias("size"), e["name"].alias("name"), e["new"].alias("new"))))
    return F.transform(order, lambda e: F.struct(F.concat(F.lit(r"(?<![\p{L}\p{N}])\Q"), F.replace(e["name"], F.lit("\\E"), F.lit("")), F.lit(r"\E(?![\p{L}\p{N}])")).alias("pattern"), e["new"].alias("new")))


def with_surrogates(docs: DataFrame, key: str, counts: bool = False) -> DataFrame:
    """``docs`` with every entity in ``text`` replaced by its surrogate; all columns are kept, and
    n_chars, if there, is the new text's length where the text changed. ``counts`` adds n_entities, the
    entities found (a known name's repeats without a title are replaced but not counted).

    The key is secret: equal keys give equal surrogates, and who knows the key can look entities up. Null and empty
    texts stay; repeated rows are replaced alike; an empty table gives no rows. Names of internal columns start
    with two underscores.
    """
    if not key:
        raise ValueError("surrogates need a secret key")
    columns = docs.columns
    text = F.col("text")
    found = F.when(text.rlike(CHEAP), F.regexp_extract_all(text, F.lit(ENTITY), F.lit(0)))
    tagged = stored(docs.withColumn("__found", found).withColumn("__found", F.when(F.size("__found") > 0, F.col("__found"))), "tagged")
    hit = tagged.where("__found is not null").withColumns({"__a": F.xxhash64("text"), "__b": F.xxhash64(F.lit(1), F.reverse("text"))})
    spoken = stored(hit.select("__a", "__b", F.explode(F.array_distinct("__found")).alias("surface")).distinct(), "spoken")
    table = surrogate_table(spoken.select("surface").distinct(), key)
    pairs = spoken.join(table.select("surface", "surrogate"), "surface")
    maps = stored(
        pairs.groupBy("__a", "__b").agg(F.map_from_entries(F.collect_list(F.struct("surface", "surrogate"))).alias("__map")).withColumn("__bare", _bare_names(F.col("__map"))), "maps"
    )
    parts = F.split(F.col("text"), ENTITY, -1)
    plain = F.transform(parts, lambda p: F.aggregate(F.col("__bare"), p, lambda t, e: F.regexp_replace(t, e["pattern"], e["new"])))
    pieces = F.zip_with(F.when(F.size("__bare") > 0, plain).otherwise(parts), F.col("__found"), lambda p, e: F.concat(p, F.coalesce(F.element_at(F.col("__map"), e), F.lit(""))))
    replaced = hit.join(maps, ["__a", "__b"]).withColumn("text", F.array_join(pieces, ""))
    if "n_chars" in columns:
        replaced = replaced.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    out = [replaced.select(*columns, F.size("__found").cast("long").alias("n_entities"))]
    out.append(tagged.where("__found is null").withColumn("n_entities", F.lit(0).cast("long")).select(*columns, "n_entities"))
    both = out[0].unionByName(out[1])
    return both if counts else both.select(*columns)
