"""PII: detected entities are replaced by keyed surrogates of the same type.

Every notation of an entity has one canonical form, and the surrogate is made from that form and laid into the notation at
hand. Digits of telephone, card and identity numbers and bits of addresses pass a keyed permutation of their own number range,
so different ones stay different; a card keeps whether its check digit fits, an address its range, a telephone its country
code. Names and mail addresses are drawn from keyed digests, keeping gender, script, capitals, separators and digit places; a
family name has one surrogate wherever it stands, so titled names and their bare repeats in a document stay together. A global
check looks for two entities with one surrogate and for surrogates that are entities themselves, of every kind; those found
get another draw, numbers and addresses by the permutation of another key.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

# Titles that announce a name, by gender, and given names by gender and script.
TITLES = {"f": "Mrs|Ms|Miss|Frau|Madame|Mme|Señora|Sra|Госпожа", "m": "Mr|Herr|Monsieur|Señor|Sr|Господин"}
GIVEN = {
    ("f", "latin"): "Ada Alma Carla Clara Dora Edith Elena Emma Flora Greta Helga Ida Irma Julia Klara Laura Lena Lina Mara Maria Nora Olga Paula Rosa Sara Selma Silvia Stella Tilda Vera Viola Wanda",
    ("m", "latin"): "Adam Albin Anton Arno Bruno Carl Conrad Emil Erik Felix Franz Georg Gustav Hans Hugo Ivan Jakob Jonas Karl Leo Linus Marco Martin Max Otto Oskar Paul Peter Rudolf Simon Theo Viktor",
    ("f", "cyrillic"): "Анна Вера Галина Дарья Елена Жанна Зоя Инна Лидия Мария Нина Ольга Раиса Софья Тамара Юлия",
    ("m", "cyrillic"): "Антон Борис Вадим Глеб Денис Егор Захар Игорь Кирилл Лев Максим Николай Олег Павел Роман Юрий",
}
SYLLABLES = {"latin": "ba be bo da de do fa fe ga go ha he ka ke la le ma me na ne pa pe ra re sa se ta te va ve wa we", "cyrillic": "ба бе бо ва ве га ге да де жа за зе ка ке ла ле ма ме на не па пе ра ре са се та те фа ха ча ша"}
_OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9]{2}|[1-9]?[0-9])"
_WORD = r"\p{L}\p{N}._%+-"
_TITLE = rf"(?<!\p{{L}})(?:{TITLES['f']}|{TITLES['m']})\.? "
#: Kind to pattern; the first that fits a match names its kind. A domain has 127 labels at most, and loops over groups are
#: bounded, because the engine of the patterns recurses in them.
PATTERNS = {
    "email": rf"(?<![{_WORD}])[{_WORD}]++@[\p{{L}}\p{{N}}-]++(?:\.[\p{{L}}\p{{N}}-]++){{1,126}}+",
    "ip": rf"(?<![0-9.\p{{L}}]){_OCTET}(?:\.{_OCTET}){{3}}(?![0-9]|\.[0-9])",
    "phone": r"(?<![0-9\p{L}])(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)|[0-9]{3})[ .-]?[0-9]{3}[ .-][0-9]{4}(?![0-9])",
    "card": r"(?<![0-9\p{L}])[0-9]{4}([ -]?)[0-9]{4}\1[0-9]{4}\1[0-9]{1,7}(?![0-9\p{L}])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "name": rf"{_TITLE}\p{{Lu}}\p{{L}}++(?: (?!(?:{TITLES['f']}|{TITLES['m']})(?!\p{{L}}))\p{{Lu}}\p{{L}}++)?",
}
ANY = "|".join(f"(?:{p.replace('([ -]?)', '(?<gap>[ -]?)').replace(chr(92) + '1', chr(92) + 'k<gap>')})" for p in PATTERNS.values())
#: In documents with a titled name every capitalised word is looked at: it may repeat the name.
WIDE = ANY + r"|(?:(?<!\p{L})\p{Lu}\p{L}++)"
HINT = rf"@[\p{{L}}\p{{N}}]|[0-9]{{3}}[ .-][0-9]{{4}}|[0-9]{{12}}|[0-9]{{4}}[ -][0-9]{{4}}|[0-9]\.[0-9]{{1,3}}\.[0-9]|[0-9]-[0-9]{{2}}-[0-9]|{_TITLE}\p{{Lu}}"
NUMBERS = ("ip", "phone", "card", "ssn")
ENTITY = "struct<kind:string,what:string>"


def let(value: Column, then) -> Column:
    """then(value) with value written once: keeps nested expressions from doubling at each use."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def kind_of(value: Column) -> Column:
    out = F.when(value.contains("@"), "email").when(value.rlike(r"^[0-9]+(\.[0-9]+){3}$"), "ip").when(value.rlike("^[0-9]{3}-[0-9]{2}-[0-9]{4}$"), "ssn")
    out = out.when(value.rlike(r"^[+(]|^[0-9]{3}[ .-]?[0-9]{3}[ .-][0-9]{4}$"), "phone").when(value.rlike("^[0-9]"), "card")
    return out.when(value.contains(" "), "name").otherwise("word")


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _bare(value: Column) -> Column:
    """A name without its title."""
    return F.regexp_replace(value, r"^\S+ ", "")


def _family(value: Column) -> Column:
    return F.regexp_extract(value, r"\S+$", 0)


def _person(value: Column) -> Column:
    """Gender and full name of a titled name."""
    return F.concat(F.when(value.rlike(rf"^(?:{TITLES['f']})\.? "), "f").otherwise("m"), F.lit("|"), _bare(value))


def normal(value: Column, kind: Column) -> Column:
    """What the notations of one entity have in common. A telephone number: country code, blank, national number, which is what
    stands from a bracket on, or the last ten digits."""
    code = F.when(value.contains("("), _digits(F.regexp_extract(value, r"^[^(]*", 0))).otherwise(F.regexp_extract(_digits(value), "^([0-9]*?)[0-9]{0,10}$", 1))
    phone = let(code, lambda c: F.concat(c, F.lit(" "), F.substring(_digits(value), F.length(c) + 1, F.length(value))))
    return F.when(kind == "email", F.lower(value)).when(kind == "name", _person(value)).when(kind.isin("ip", "family"), value).when(kind == "phone", phone).otherwise(_digits(value))


def _draw(key: str, kind: Column | str, what: Column, attempt: Column, salt: str) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), F.lit(kind) if isinstance(kind, str) else kind, attempt.cast("string"), F.lit(salt), what), 256)


def _number(digest: Column, at: Column | int, below: Column | int) -> Column:
    """A number below a bound of up to 10**10 from a hexadecimal digest."""
    return F.pmod(F.conv(F.substring(digest, F.lit(at) if isinstance(at, int) else at, F.lit(15)), 16, 10).cast("long"), F.lit(below) if isinstance(below, int) else below)


def _nth_key(key: str, attempt: Column) -> Column:
    """The key itself at first, then one of its own for each attempt."""
    return F.when(attempt == 0, F.lit(key)).otherwise(F.concat_ws("|", F.lit(key), attempt.cast("string")))


def _halves(key: Column, of: Column, left: Column, right: Column, a: Column, b: Column, rounds: int = 4) -> Column:
    """Keyed permutation of pairs below (a, b): each half is shifted in turn by a digest of the other. Struct l, r."""

    args = F.struct(key.alias("key"), of.alias("of"), left.alias("l"), right.alias("r"), a.alias("a"), b.alias("b"))
    shifted = lambda x, i, side, by, from_, below: F.pmod(from_ + _number(F.sha2(F.concat_ws("|", x["key"], x["of"], i, F.lit(side), by), 256), 1, 10**10), below)

    def run(x):
        def turn(s, i):
            left = let(shifted(x, i, "l", s["r"], s["l"], x["a"]), lambda l: F.struct(l.alias("l"), s["r"].alias("r")))
            return let(left, lambda t: F.struct(t["l"].alias("l"), shifted(x, i, "r", t["l"], t["r"], x["b"]).alias("r")))

        return F.aggregate(F.sequence(F.lit(1), F.lit(rounds)), F.struct(x["l"].alias("l"), x["r"].alias("r")), turn)

    return let(args, run)


def permuted(digits: Column, key: Column | str, kind: Column) -> Column:
    """Keyed permutation of the digit strings of each length up to 20."""
    key = F.lit(key) if isinstance(key, str) else key
    tens = lambda k: F.rpad(F.lit("1"), k + 1, "0").try_cast("long")

    def of(d):
        n = F.length(d["d"])
        a = F.floor(n / 2).cast("int")
        left, right = F.coalesce(F.substring(d["d"], F.lit(1), a).try_cast("long"), F.lit(0)), F.coalesce(F.substring(d["d"], a + 1, n).try_cast("long"), F.lit(0))
        end = _halves(d["key"], F.concat_ws("|", d["kind"], n), left, right, tens(a), tens(n - a))
        return let(end, lambda e: F.concat(F.when(a > 0, F.lpad(e["l"].cast("string"), a, "0")).otherwise(""), F.lpad(e["r"].cast("string"), n - a, "0")))

    return let(F.struct(digits.alias("d"), key.alias("key"), kind.alias("kind")), of)


def _check_digit(payload: Column) -> Column:
    """The digit that makes the alternating digit sum of payload and digit a multiple of ten."""
    each = F.transform(F.reverse(F.split(payload, "")), lambda d, i: F.coalesce(d.try_cast("int"), F.lit(0)) * (2 - i % 2))
    total = F.aggregate(each, F.lit(0), lambda acc, x: acc + F.when(x > 9, x - 9).otherwise(x))
    return F.pmod(10 - total, F.lit(10))


def _card(digits: Column, key: Column) -> Column:
    """All digits but the last permuted; the last one is as far from the check digit as before."""
    n = F.length(digits)
    head, last = F.substring(digits, F.lit(1), n - 1), F.substring(digits, n, F.lit(1)).try_cast("int")
    return let(permuted(head, key, F.lit("card")), lambda new: F.concat(new, F.pmod(last - _check_digit(head) + _check_digit(new), F.lit(10)).cast("string")))


def ip_range(ip: Column) -> Column:
    """Bits of an address that its range leaves free: private, loopback, link-local and reserved ranges stay as they are."""
    a, b = F.split_part(ip, F.lit("."), F.lit(1)).try_cast("int"), F.split_part(ip, F.lit("."), F.lit(2)).try_cast("int")
    return F.when(a.isin(0, 10, 127) | (a >= 224), 24).when((a == 172) & b.between(16, 31), 20).when(((a == 192) & (b == 168)) | ((a == 169) & (b == 254)), 16).otherwise(32)


def _ip(ip: Column, key: Column, tries: int = 16) -> Column:
    """The free bits permuted; a public address walks on until it is public again."""
    of_bits = lambda v: F.concat_ws(".", *(F.pmod(F.shiftright(v, s), F.lit(256)) for s in (24, 16, 8, 0)))
    number = F.aggregate(F.split(ip, r"\."), F.lit(0).cast("long"), lambda acc, x: acc * 256 + F.coalesce(x.try_cast("long"), F.lit(0)))
    two_to = lambda n: F.call_function("shiftleft", F.lit(1).cast("long"), n.cast("int"))

    def walk(x):
        base = x["n"] - F.pmod(x["n"], x["low"])
        div = lambda v, by: F.call_function("div", v, by)

        def step(v, i):
            end = _halves(x["key"], F.concat_ws("|", F.lit("ip"), x["bits"]), div(v, x["b"]), F.pmod(v, x["b"]), div(x["low"], x["b"]), x["b"])
            return F.when((i > 1) & (ip_range(of_bits(base + v)) == x["bits"]), v).otherwise(let(end, lambda e: e["l"] * x["b"] + e["r"]))

        return let(base + F.aggregate(F.sequence(F.lit(1), F.when(x["bits"] == 32, tries).otherwise(1)), F.pmod(x["n"], x["low"]), step), of_bits)

    args = lambda bits: F.struct(number.alias("n"), bits.alias("bits"), two_to(bits).alias("low"), two_to(F.floor(bits / 2)).alias("b"), key.alias("key"))
    return let(let(ip_range(ip), args), walk)


def _digits_in(value: Column, digits: Column) -> Column:
    """value with its digits replaced in turn."""
    return F.array_join(F.zip_with(F.split(value, "[0-9]", -1), F.array_append(F.split(digits, ""), F.lit("")), lambda gap, d: F.concat(F.coalesce(gap, F.lit("")), F.coalesce(d, F.lit("")))), "")


def _script(value: Column) -> Column:
    return F.when(value.rlike(r"\p{IsCyrillic}"), "cyrillic").otherwise("latin")


def _pick(options: Column, digest: Column, at: Column | int) -> Column:
    """One of the options, which stand in one string."""
    return let(F.split(options, " "), lambda each: F.get(each, _number(digest, at, F.size(each)).cast("int")))


def _syllables(value: Column, digest: Column, n: int) -> Column:
    options = F.when(_script(value) == "cyrillic", F.lit(SYLLABLES["cyrillic"])).otherwise(F.lit(SYLLABLES["latin"]))
    return F.array_join(F.transform(F.sequence(F.lit(3), F.lit(3 * n), F.lit(3)), lambda at: _pick(options, digest, at)), "")


def family_surrogate(family: Column, key: str, attempt: Column) -> Column:
    """A drawn family name; in Cyrillic script with an ending of the same gender."""
    made = let(_draw(key, "family", family, attempt, "a"), lambda digest: F.initcap(_syllables(family, digest, 8)))
    return F.concat(made, F.when(_script(family) == "cyrillic", F.when(family.rlike("[аяАЯ]$"), "ва").otherwise("в")).otherwise(""))


def given_surrogate(person: Column, key: str, attempt: Column) -> Column:
    """A given name of the person's gender and script; after a collision one made of syllables."""
    female, cyrillic = person.startswith("f|"), _script(person) == "cyrillic"

    def of(digest):
        pool = F.lit(None)
        for (gender, script), options in GIVEN.items():
            pool = F.when((female == F.lit(gender == "f")) & (cyrillic == F.lit(script == "cyrillic")), F.lit(options)).otherwise(pool)
        known = _pick(pool, digest, 1)
        made = F.concat(F.initcap(_syllables(person, digest, 4)), F.when(female, F.when(cyrillic, "на").otherwise("na")).otherwise(F.when(cyrillic, "р").otherwise("r")))
        return F.when(attempt == 0, known).otherwise(made)

    return let(_draw(key, "name", person, attempt, "a"), of)


def entity_of(value: Column, kind: Column) -> Column:
    """The entities (kind, what) that a found piece stands for: a full name is a person and a family name."""
    plain = F.array(F.struct(kind.alias("kind"), normal(value, kind).alias("what")))
    family = F.struct(F.lit("family").alias("kind"), _family(value).alias("what"))
    person = F.struct(F.lit("name").alias("kind"), _person(value).alias("what"))
    named = F.when(_bare(value).contains(" "), F.array(person, family)).otherwise(F.array(family))
    return F.when(kind == "word", F.array().cast(f"array<{ENTITY}>")).when(kind == "name", named).otherwise(plain)


def surrogate(kind: Column, what: Column, key: str, attempt: Column) -> Column:
    """The canonical surrogate of one entity: of a number its digits, of a person the given name."""
    # Mail: letters by digest, at least twelve, then the digit places of the local part; a reserved domain.
    local = F.regexp_extract(what, "^[^@]*", 0)

    def mail(digest):
        letters = F.translate(F.substring(digest, 1, 14), "0123456789abcdef", "bcdfghklmnprstvw")
        shape = F.concat(letters, F.when(local.rlike("[0-9]"), F.concat(F.regexp_extract(local, "[^0-9]*?([._+-]?)[0-9]", 1), F.lpad(_number(digest, 20, 100).cast("string"), 2, "0"))).otherwise(""))
        return F.concat(shape, F.lit("@mail"), _number(digest, 40, 10).cast("string"), F.lit(".example.org"))

    def number(nth):
        code = F.regexp_extract(what, "^[0-9]*", 0)
        phone = F.concat(code, F.lit(" "), permuted(F.regexp_extract(what, "[0-9]*$", 0), nth, F.concat_ws("|", F.lit("phone"), code)))
        return F.when(kind == "ip", _ip(what, nth)).when(kind == "phone", phone).when(kind == "card", _card(what, nth)).otherwise(permuted(what, nth, F.lit("ssn")))

    out = F.when(kind == "email", let(_draw(key, kind, what, attempt, "a"), mail)).when(kind == "family", family_surrogate(what, key, attempt)).when(kind == "name", given_surrogate(what, key, attempt))
    return out.otherwise(let(_nth_key(key, attempt), number))


def entities(text: Column) -> Column:
    """The pieces of a text that patterns find, in order; in a text with a titled name, capitalised words too."""
    return F.when(text.rlike(rf"{_TITLE}\p{{Lu}}"), F.regexp_extract_all(text, F.lit(WIDE), F.lit(0))).otherwise(F.regexp_extract_all(text, F.lit(ANY), F.lit(0)))


def _gaps(text: Column) -> Column:
    return F.when(text.rlike(rf"{_TITLE}\p{{Lu}}"), F.split(text, WIDE, -1)).otherwise(F.split(text, ANY, -1))


def _listed(found: Column) -> Column:
    return F.array_distinct(F.flatten(F.transform(found, lambda v: let(kind_of(v), lambda k: entity_of(v, k)))))


def replace_entities(docs: DataFrame, key: str = "surrogates", carry=()) -> DataFrame:
    """doc_id, carry, text with surrogates, n_entities and kinds for each row of docs (doc_id, text).

    Null texts stay null and have no entity; texts without one stay as they are; repeated rows are treated alike; a surrogate
    is never taken for another entity's by the check. A bare word that is the family name of a titled name in the same document
    follows it, and so does the given name before it. Numbers of a range of which the corpus holds nearly all stay distinct, but
    their surrogates may be other numbers of it. Other columns are ignored, but for those in carry, whatever their names. The
    key is a secret of the caller. An empty table gives no row.
    """
    names = {c: f"_carried{i}" for i, c in enumerate(carry)}
    base = docs.select("doc_id", "text", *(F.col(c).alias(n) for c, n in names.items()))
    some = base.filter(F.col("text").rlike(HINT)).select("doc_id", "text")
    each = stored(some.select(F.explode(_listed(entities(F.col("text")))).alias("e")).select("e.kind", "e.what").distinct(), "entities")
    again = _collisions(each, key)
    rows = base.withColumn("_found", F.when(F.col("text").rlike(HINT), entities(F.col("text"))))
    attempt = lambda kind, what: F.lit(0)
    if again is not None:
        uid = F.xxhash64("doc_id", "text")
        held = some.select(uid.alias("_uid"), F.explode(_listed(entities(F.col("text")))).alias("e")).select("_uid", "e.kind", "e.what")
        entry = F.struct(F.concat_ws(":", "kind", "what"), "attempt")
        maps = held.join(again, ["kind", "what"]).groupBy("_uid").agg(F.map_from_entries(F.collect_set(entry)).alias("_again"))
        rows = rows.withColumn("_uid", uid).join(maps, "_uid", "left")
        attempt = lambda kind, what: F.coalesce(F.try_element_at("_again", F.concat_ws(":", kind, what)), F.lit(0))
    rows = rows.withColumn("_at", F.transform("_found", lambda v: let(kind_of(v), lambda k: F.struct(v.alias("v"), k.alias("kind"), F.when(k != "word", normal(v, k)).alias("what")))))
    titled = F.transform(F.filter("_at", lambda x: x["kind"] == "name"), lambda x: x["v"])
    rows = rows.withColumn("_titled", titled)
    rows = rows.withColumns({"_families": F.array_distinct(F.transform("_titled", _family)), "_persons": F.array_distinct(F.transform("_titled", _person)), "_gaps": F.when(F.size("_found") > 0, _gaps(F.col("text")))})
    rows = rows.withColumn("_pairs", F.transform("_persons", lambda p: F.regexp_replace(p, "^..", "")))

    def person_at(v, i):
        """The person whose bare given name stands here, if the family name follows."""
        at = lambda pair: F.when(F.get("_gaps", i + 1) == " ", F.array_position("_pairs", pair))
        return F.get("_persons", let(F.concat(v, F.lit(" "), F.get("_found", i + 1)), at).cast("int") - 1)

    family = lambda f: family_surrogate(f, key, attempt(F.lit("family"), f))
    given = lambda p: let(p, lambda q: given_surrogate(q, key, attempt(F.lit("name"), q)))

    def swapped(x, i):
        v, kind, what = x["v"], x["kind"], x["what"]
        named = F.concat(F.regexp_extract(v, r"^\S+ ", 0), F.when(_bare(v).contains(" "), F.concat(given(what), F.lit(" "))).otherwise(""), let(_family(v), family))
        word = F.when(F.array_contains("_families", v), family(v)).otherwise(let(person_at(v, i), lambda p: F.when(p.isNotNull(), given(p)).otherwise(v)))
        made = let(attempt(kind, what), lambda n: surrogate(kind, what, key, n))
        laid = F.when(kind.isin("email", "ip"), made).otherwise(_digits_in(v, _digits(made)))
        return F.when(kind == "word", F.when(F.size("_titled") > 0, word).otherwise(v)).when(kind == "name", named).otherwise(laid)

    rows = rows.withColumn("_new", F.transform("_at", swapped))
    replaced = F.transform("_at", lambda x, i: F.when(x["kind"] != "word", x["kind"]).when(x["v"] != F.get("_new", i), "name"))
    rows = rows.withColumn("_kinds", F.filter(replaced, lambda k: k.isNotNull()))
    whole = F.array_join(F.zip_with("_gaps", "_new", lambda gap, s: F.concat(gap, F.coalesce(s, F.lit("")))), "")
    return rows.select("doc_id", *(F.col(n).alias(c) for c, n in names.items()), F.when(F.size("_kinds") > 0, whole).otherwise(F.col("text")).alias("text"), F.coalesce(F.size("_kinds"), F.lit(0)).cast("long").alias("n_entities"), F.array_join(F.array_sort(F.array_distinct("_kinds")), ",").alias("kinds"))


def _class(kind: Column, what: Column) -> Column:
    """Numbers that one permutation maps onto each other."""
    return F.when(kind == "ip", F.concat_ws("|", kind, ip_range(what), F.when(ip_range(what) < 32, F.split_part(what, F.lit("."), F.lit(1))))).when(kind == "phone", F.concat_ws("|", kind, F.split_part(what, F.lit(" "), F.lit(1)), F.length(what))).otherwise(F.concat_ws("|", kind, F.length(what)))


def _collisions(each: DataFrame, key: str, rounds: int = 12) -> DataFrame | None:
    """Entities that need another draw, with its number; None if all surrogates differ from each other and from all entities.

    Numbers that do not settle are of a range that the corpus nearly fills: all of the range keep their first draw, which is
    distinct by itself."""
    again = None
    now = each.withColumn("attempt", F.lit(0))
    for turn in range(rounds + 1):
        made = surrogate(F.col("kind"), F.col("what"), key, F.col("attempt"))
        out = F.when(F.col("kind") == "name", F.concat(F.substring("what", 1, 2), made, F.lit(" "), _family(F.col("what")))).otherwise(made)
        drawn = stored(now.withColumn("out", out), f"drawn-{uuid.uuid4().hex[:6]}")
        shared = drawn.groupBy("kind", "out").agg(F.count("*").alias("n"), F.min("what").alias("keeps")).filter("n > 1")
        clash = drawn.join(shared, ["kind", "out"]).filter("what <> keeps").select("kind", "what")
        taken = drawn.join(each.select("kind", F.col("what").alias("out")), ["kind", "out"], "left_semi").select("kind", "what")
        bad = stored(clash.union(taken).distinct(), "collisions")
        if bad.isEmpty():
            return again
        if turn < rounds:
            step = drawn.join(bad.withColumn("more", F.lit(1)), ["kind", "what"], "left").select("kind", "what", (F.col("attempt") + F.coalesce("more", F.lit(0))).alias("attempt"))
        else:
            if not bad.filter(~F.col("kind").isin(*NUMBERS)).isEmpty():
                raise ValueError("surrogates still collide; choose another key")
            full = bad.select(_class(F.col("kind"), F.col("what")).alias("range")).distinct().withColumn("full", F.lit(True))
            step = drawn.withColumn("range", _class(F.col("kind"), F.col("what"))).join(full, "range", "left").select("kind", "what", F.when(F.col("full"), 0).otherwise(F.col("attempt")).alias("attempt"))
        now = stored(step, "attempts")
        again = now.filter("attempt > 0").select("kind", "what", "attempt")
    return again
