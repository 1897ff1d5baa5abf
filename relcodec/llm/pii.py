r"""Personal data replaced by surrogates.

One pattern finds e-mail addresses, assigned secrets, account numbers, cards, phones, social-security numbers, IP
addresses and titled names; card numbers of no given layout must satisfy the Luhn check. Each entity gets a surrogate
made from a keyed hash (HMAC) of its kind and normal form, so one entity has one surrogate everywhere, whatever
document or format it stands in (phones and cards are the same if their digits are).

Surrogates keep kind and format: digits are laid into the original punctuation, cards that satisfy the Luhn check still
do, secrets keep their alphabet and length, letters keep their case. A person is family name and given names, each
with a surrogate of its own: so Mrs Jane Doe, Mrs. Doe and Mr. John Doe share the family name's. The title stays; a
given name's surrogate has the gender of the title, else that of the given name where the lists know it, else neither.
Names in Latin, Cyrillic and Greek script get names in theirs, words in capitals get capitals. A family name met with a
title is replaced wherever it recurs in that text as a capitalised word, and so are its given names beside it.

Distinctness is checked over the whole corpus: distinct entities are grouped by surrogate, and one that shares its
surrogate with another, or whose surrogate is itself an entity of the corpus, moves to its next attempt. Entities left
after `max_rounds` attempts get surrogates widened by their rank, which are checked once more (an error if any is
shared). Attempts above zero are a small table; documents meet it by a join only if it has rows. Texts are read twice
(entities, replacement), never shuffled unless an attempt moved.

Everything is built of DataFrame functions. Defined cases: null text stays null with no entities; empty texts stay;
an entity at either end of a text is replaced; adjoining entities are separate; equal entities get equal surrogates and
repeated rows are replaced alike; very long texts are read whole; an empty table gives an empty result; other columns
pass through whatever their names, except that `n_entities` is set anew.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.llm import common

#: The registered query's key. `replace` takes the caller's own.
DEMO_KEY = "surrogate-key-1"
MAX_ROUNDS = 16
#: Titles by the gender they tell.
FEMALE_TITLES = "Mrs|Ms|Miss|Frau|Madame|Mme|Señora|Sra|Signora|Госпожа|госпожа|Κυρία|κυρία"
MALE_TITLES = "Mr|Herr|Monsieur|Señor|Sr|Signor|Господин|господин|Κύριος|κύριος"
NEUTRAL_TITLES = "Dr|Prof|Professor|Доктор|доктор"
_NAME_WORD = r"\p{Lu}[\p{L}'’-]*\p{L}"
#: Kinds in the order they are tried, with their patterns.
KINDS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "secret": r'(?i:token|password|passwd|pwd|secret|api_?key|access_?key)\s*[=:]\s*"?[A-Za-z0-9_+/-]{8,}"?',
    "account": r"\b[A-Z]{2}[0-9]{2}[A-Z0-9]{10,30}\b",
    "phone": r"\+?[0-9]{1,3}[ .-]?\([0-9]{2,4}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}\b|\+[0-9]{1,3}(?:[ .-][0-9]{2,4}){2,5}\b|\b[0-9]{3}[.-][0-9]{3}[.-][0-9]{4}\b",
    "card": r"\b[0-9]{4}[ -][0-9]{4}[ -][0-9]{4}[ -][0-9]{4}\b|\b[0-9]{13,19}\b",
    "ssn": r"\b[0-9]{3}-[0-9]{2}-[0-9]{4}\b",
    "ip": r"(?=[0-9])(?<![0-9.v])(?<!ersion )(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?:\.(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])){3}(?!\.?[0-9])",
    "person": rf"(?=[A-Z]|[^\x00-\x7F])(?<![\p{{L}}\p{{N}}])(?:{FEMALE_TITLES}|{MALE_TITLES}|{NEUTRAL_TITLES})\.? (?:\p{{Lu}}\. ){{0,2}}{_NAME_WORD}(?: {_NAME_WORD}){{0,2}}",
}
PATTERN = "|".join(f"(?:{p})" for p in KINDS.values())
#: What every match holds one of: a text with none of them has no entity, and the patterns are not tried on it.
HINT = "[0-9@=:]"
TITLE_HINTS = ("Mr", "Ms", "Miss", "Frau", "Mme", "Madame", "Señor", "Sr", "Signor", "Monsieur", "Herr", "Dr", "Prof", "осподин", "оспожа", "октор", "υρία", "ύριος")
#: Stands around matches for a moment; texts that hold it are cut by the pattern once more instead.
MARK = "\ue0f1"
#: Common given names by gender (to tell a gender by), and given names of surrogates by script and gender.
KNOWN = {
    "f": "anna|maria|jane|mary|susan|linda|emma|laura|sophie|julia|sarah|claire|marie|elena|lucia|carmen|ana|eva|ingrid|petra|sabine|monika|nina|olga|анна|мария|елена|ольга|наталья|ирина|татьяна|μαρία|ελένη|άννα",
    "m": "john|james|peter|paul|david|michael|thomas|robert|hans|karl|stefan|jean|pierre|louis|jose|juan|carlos|luis|marco|ivan|max|felix|tom|george|иван|пётр|петр|сергей|алексей|дмитрий|николай|γιώργος|νίκος|ιωάννης",
}
GIVEN = {
    "latin": {"f": "Alma,Berta,Clara,Dora,Edith,Flora,Greta,Hanna,Irma,Karla,Lena,Marta,Nora,Paula,Rosa,Vera", "m": "Adam,Bruno,Carl,Emil,Georg,Hugo,Jakob,Konrad,Leo,Martin,Nils,Oscar,Quentin,Ralf,Simon,Viktor",
              "n": "Alex,Chris,Dominique,Eli,Jules,Kim,Luca,Mika,Noa,Pat,Quinn,Robin,Sam,Toni,Val,Yael"},
    "cyrillic": {"f": "Алла,Вера,Галина,Дарья,Жанна,Зоя,Инна,Лидия", "m": "Антон,Борис,Вадим,Глеб,Егор,Игорь,Лев,Олег", "n": "Валя,Женя,Паша,Саша,Слава,Тоня,Шура,Юля"},
    "greek": {"f": "Δάφνη,Ειρήνη,Ζωή,Θάλεια,Ίρις,Κλειώ,Μυρτώ,Χλόη", "m": "Άρης,Βίκτωρ,Ηλίας,Θάνος,Λέων,Μάρκος,Πάρης,Φάνης", "n": "Άλκη,Βάιος,Γωγώ,Ζήση,Κίμων,Λίνο,Ρένο,Σάσα"},
}
SYLLABLES = {
    "latin": "ba,be,bi,bo,da,de,di,do,ka,ke,ki,ko,la,le,li,lo,ma,me,mi,mo,na,ne,ni,no,ra,re,ri,ro,sa,se,si,so",
    "cyrillic": "ба,бе,би,бо,да,де,ди,до,ка,ке,ки,ко,ла,ле,ли,ло,ма,ме,ми,мо,на,не,ни,но,ра,ре,ри,ро,са,се,си,со",
    "greek": "βα,βε,βι,βο,δα,δε,δι,δο,κα,κε,κι,κο,λα,λε,λι,λο,μα,με,μι,μο,να,νε,νι,νο,ρα,ρε,ρι,ρο,σα,σε,σι,σο",
}
#: Hash bytes with a draw of their own (family syllables 1 to 6, given names 7 to 12).
FAMILY_BYTES, GIVEN_BYTES = range(1, 7), range(7, 13)


def luhn(digits: Column) -> Column:
    """Sum of the Luhn check over all digits, modulo 10 (0: valid)."""
    n = F.length(digits)
    values = F.transform(F.split(digits, ""), lambda c, i: common.let(
        c.cast("int") * F.when((n - i) % 2 == 0, 2).otherwise(1), lambda d: F.when(d > 9, d - 9).otherwise(d)))
    return F.aggregate(values, F.lit(0), lambda a, b: a + b) % 10


def kind_of(raw: Column) -> Column:
    """Kind of a match of the pattern; null for a bare run of digits that fails the Luhn check."""
    out = F.lit("person")
    for kind, pattern in reversed(list(KINDS.items())[:-1]):
        out = F.when(raw.rlike(f"^(?:{pattern})$"), kind).otherwise(out)
    return F.when(raw.rlike("^[0-9]{13,19}$") & (luhn(raw) != 0), None).otherwise(out)


def secret_head(raw: Column) -> Column:
    return F.regexp_extract(raw, r'^[A-Za-z_]+\s*[=:]\s*"?', 0)


def title_of(raw: Column) -> Column:
    return F.regexp_extract(raw, r"^[^ ]+ ", 0)


def name_words(raw: Column) -> Column:
    return F.split(F.substring(raw, F.length(title_of(raw)) + 1, F.length(raw)), " ")


def gender_of(raw: Column) -> Column:
    """f, m or n by the title, else by the first given name."""
    first = F.lower(F.regexp_extract(raw, r"^[^ ]+ ([^ ]+) ", 1))
    return (F.when(raw.rlike(rf"^(?:{FEMALE_TITLES})\b"), "f").when(raw.rlike(rf"^(?:{MALE_TITLES})[. ]"), "m")
            .when(first.rlike(f"^(?:{KNOWN['f']})$"), "f").when(first.rlike(f"^(?:{KNOWN['m']})$"), "m").otherwise("n"))


def parts(raw: Column) -> Column:
    """(kind, norm) of the entities in a match: one, but for persons, whose family and given names are one each."""
    def of_person(words: Column) -> Column:
        last = F.size(words) - 1
        return F.transform(words, lambda w, i: F.struct(F.when(i == last, F.lit("family")).otherwise(F.concat(F.lit("given_"), gender_of(raw))).alias("kind"), F.lower(w).alias("norm")))

    kind = kind_of(raw)
    one = F.array(F.struct(kind.alias("kind"), normal(kind, raw).alias("norm")))
    return F.when(kind == "person", of_person(name_words(raw))).when(kind.isNotNull(), one).otherwise(F.array().cast("array<struct<kind:string,norm:string>>"))


def normal(kind: Column, raw: Column) -> Column:
    """What stays the same when an entity is written otherwise."""
    value = F.regexp_replace(F.substring(raw, F.length(secret_head(raw)) + 1, F.length(raw)), '"$', "")
    return (F.when(kind == "email", F.lower(raw)).when(kind.isin("phone", "card", "ssn"), F.regexp_replace(raw, "[^0-9]", ""))
            .when(kind == "secret", value).otherwise(raw))


def hmac512(key: str, message: Column) -> Column:
    """HMAC-SHA-512 in hexadecimal digits. The key's pads are constants of the plan, so no row works on the key."""
    own = key.encode()
    own = (hashlib.sha512(own).digest() if len(own) > 128 else own).ljust(128, b"\0")
    inner, outer = (F.lit(bytearray(b ^ pad for b in own)) for pad in (0x36, 0x5C))
    return F.sha2(F.concat(outer, F.unhex(F.sha2(F.concat(inner, F.encode(message, "UTF-8")), 512))), 512)


def stream(kind: Column, norm: Column, attempt: Column, key: str) -> Column:
    """256 hexadecimal digits from the key and the entity."""
    seed = F.concat_ws("|", kind, norm, attempt.cast("string"))
    return F.concat(hmac512(key, F.concat(seed, F.lit("|a"))), hmac512(key, F.concat(seed, F.lit("|b"))))


def byte(hexes: Column, i: Column) -> Column:
    return F.conv(F.substring(hexes, (i % 128) * 2 + 1, F.lit(2)), 16, 10).cast("int")


def scrambled(value: Column, hexes: Column) -> Column:
    """Every ASCII letter and digit replaced by one of its class; the rest stays."""
    def one(c: Column, i: Column) -> Column:
        v = byte(hexes, i)
        pick = lambda letters, n: F.substring(F.lit(letters), (v % n) + 1, F.lit(1))
        return (F.when(c.between("0", "9"), pick("0123456789", 10)).when(c.rlike("^[a-z]$"), pick("abcdefghijklmnopqrstuvwxyz", 26))
                .when(c.rlike("^[A-Z]$"), pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ", 26)).otherwise(c))
    return F.array_join(F.transform(F.split(value, ""), one), "")


def by_script(norm: Column, made) -> Column:
    return F.when(norm.rlike(r"\p{IsCyrillic}"), made("cyrillic")).when(norm.rlike(r"\p{IsGreek}"), made("greek")).otherwise(made("latin"))


def listed(names: str) -> Column:
    """A constant array: one literal once folded, so that plans stay small."""
    return F.split(F.lit(names), ",")


def picked(names: Column, hexes: Column, at: Column) -> Column:
    """One of the names for each hash byte of `at`."""
    return F.transform(at, lambda i: F.element_at(names, byte(hexes, i) % F.size(names) + 1))


def surrogate(kind: Column, norm: Column, attempt: Column, key: str = DEMO_KEY, max_rounds: int = MAX_ROUNDS) -> Column:
    """The normal form of the entity's replacement. From attempt max_rounds on it is widened by the attempt's rank."""
    extra = F.when(attempt >= max_rounds, (attempt - max_rounds).cast("string")).otherwise("")

    def made(h: Column) -> Column:
        digits = F.translate(h, "abcdef", "012345")
        body = F.concat(F.substring(norm, 1, 1), F.substring(digits, F.lit(1), F.length(norm) - 2), extra)
        checked = F.concat(body, ((10 - luhn(F.concat(body, F.lit("0")))) % 10).cast("string"))
        card = F.when(luhn(norm) == 0, checked).otherwise(F.concat(body, F.substring(digits, 200, 1)))
        host = F.concat(F.substring(hmac512(key, F.concat(F.lit("host|"), F.regexp_extract(norm, "@(.*)$", 1))), 1, 8), F.lit(".example"))
        email = F.concat(scrambled(F.regexp_extract(norm, "^[^@]+", 0), h), F.when(extra != "", F.concat(F.lit("."), extra)).otherwise(""), F.lit("@"), host)
        secret = F.concat(F.when(norm.rlike("^[0-9a-f]+$"), F.rpad(F.substring(h, F.lit(1), F.length(norm)), F.length(norm), h)).otherwise(scrambled(norm, h)), extra)
        octet = lambda i: (byte(h, F.lit(i)) % 254 + 1).cast("string")
        # A rank past the rounds counts addresses of the block 10.0.0.0/8.
        ip = F.when(extra != "", F.concat_ws(".", F.lit("10"), *[(F.shiftright(attempt - max_rounds, s) % 256).cast("string") for s in (16, 8, 0)])).otherwise(F.concat_ws(".", *[octet(i) for i in range(4)]))
        syllables = by_script(norm, lambda s: listed(SYLLABLES[s]))
        # Ranks are told in syllables, as names have no digits.
        tail = F.array_join(F.transform(F.filter(F.split(extra, ""), lambda d: d != ""), lambda d: F.element_at(syllables, d.cast("int") + 1)), "")
        family = F.concat(F.initcap(F.array_join(picked(syllables, h, F.array(*[F.lit(i) for i in FAMILY_BYTES])), "")), tail)
        # One name at first, more of them joined where that was taken.
        names = by_script(norm, lambda s: F.when(kind == "given_f", listed(GIVEN[s]["f"])).when(kind == "given_m", listed(GIVEN[s]["m"])).otherwise(listed(GIVEN[s]["n"])))
        several = F.concat(F.array_join(picked(names, h, F.slice(F.array(*[F.lit(i) for i in GIVEN_BYTES]), F.lit(1), F.least(F.lit(len(GIVEN_BYTES)), attempt + 1))), "-"), tail)
        initial = F.concat(F.upper(F.substring(F.element_at(syllables, byte(h, F.lit(0)) % F.size(syllables) + 1), 1, 1)), F.when(norm.endswith("."), ".").otherwise(""))
        given = F.when(F.length(norm) < 3, initial).otherwise(several)
        return (F.when(kind == "email", email).when(kind == "card", card).when(kind == "ip", ip)
                .when(kind.isin("phone", "ssn"), F.concat(F.substring(norm, 1, 1), F.substring(digits, F.lit(1), F.length(norm) - 1), extra))
                .when(kind == "secret", secret).when(kind == "account", F.concat(F.substring(norm, 1, 2), scrambled(F.substring(norm, F.lit(3), F.length(norm)), h), extra))
                .when(kind == "family", family).otherwise(given))
    return common.let(stream(kind, norm, attempt, key), made)


def laid_out(kind: Column, raw: Column, replacement: Column) -> Column:
    """The replacement in the format of the original."""
    def put(acc: Column, c: Column) -> Column:
        digit = c.between("0", "9")
        return F.struct(F.concat(acc["text"], F.when(digit, F.substring(replacement, acc["k"], F.lit(1))).otherwise(c)).alias("text"), (acc["k"] + digit.cast("int")).alias("k"))
    digits = F.aggregate(F.split(raw, ""), F.struct(F.lit("").alias("text"), F.lit(1).alias("k")), put, lambda acc: F.concat(acc["text"], F.substring(replacement, acc["k"], F.length(replacement))))
    head = secret_head(raw)
    quoted = F.concat(head, replacement, F.when(raw.endswith('"'), '"').otherwise(""))
    return F.when(kind.isin("phone", "card", "ssn"), digits).when(kind == "secret", quoted).otherwise(replacement)


def hinted(text: Column) -> Column:
    out = text.rlike(HINT)
    for title in TITLE_HINTS:
        out = out | F.contains(text, F.lit(title))
    return out


def matches(text: Column) -> Column:
    """All matches of the pattern in order; none (and no search) without a hint of one."""
    return F.when(hinted(text), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0))).otherwise(F.array().cast("array<string>"))


def cut_up(text: Column) -> Column:
    """(between, raw): the pattern's matches and what lies around them, one more piece than matches; by one search."""
    odd = lambda rest: lambda _, i: i % 2 == rest
    marked = F.split(F.regexp_replace(text, PATTERN, f"{MARK}$0{MARK}"), MARK, -1)
    once = common.let(marked, lambda m: F.struct(F.filter(m, odd(0)).alias("between"), F.filter(m, odd(1)).alias("raw")))
    twice = F.struct(F.split(text, PATTERN, -1).alias("between"), matches(text).alias("raw"))
    none = F.struct(F.array(text).alias("between"), F.array().cast("array<string>").alias("raw"))
    return F.when(text.isNull() | ~hinted(text), none).when(F.contains(text, F.lit(MARK)), twice).otherwise(once)


def entities(docs: DataFrame) -> DataFrame:
    """doc_id, kind, norm: a row per entity found (a family or given name is one)."""
    found = docs.select("doc_id", F.explode(matches(F.col("text"))).alias("raw"))
    return found.select("doc_id", F.explode(parts(F.col("raw"))).alias("e")).select("doc_id", "e.kind", "e.norm")


def moved(found: DataFrame, key: str = DEMO_KEY, max_rounds: int = MAX_ROUNDS) -> DataFrame:
    """kind, norm, attempt of the entities whose first surrogate was taken. Initials are not told apart."""
    known = common.materialise(found.select("kind", "norm").filter("not (kind like 'given_%' and length(norm) < 3)").distinct())
    now = known.withColumn("attempt", F.lit(0))
    out = now.filter("attempt > 0")
    for r in range(max_rounds + 1):
        made = common.materialise(now.withColumn("s", surrogate(F.col("kind"), F.col("norm"), F.col("attempt"), key, max_rounds)))
        # Of entities with one surrogate the smallest keeps it; genders share no name.
        shared = made.groupBy("kind", "s").agg(F.count(F.lit(1)).alias("n"), F.min("norm").alias("first")).filter("n > 1").select("kind", "s", "first")
        again = made.join(shared, ["kind", "s"]).filter("norm <> first").select("kind", "norm")
        names = known.select(F.col("kind").alias("_kind"), F.lower("norm").alias("_s")).distinct()
        real = made.join(names, (F.col("kind") == F.col("_kind")) & (F.lower("s") == F.col("_s")), "left_semi").select("kind", "norm")
        again = common.materialise(again.union(real).distinct())
        if again.isEmpty():
            return common.materialise(out)
        if r == max_rounds:
            raise ValueError("surrogates are not distinct: a space of surrogates is exhausted")
        # The last time every entity left gets a rank of its own.
        step = F.lit(1) if r < max_rounds - 1 else F.row_number().over(W.partitionBy("kind").orderBy("norm"))
        again = again.withColumn("more", step)
        now = made.drop("s").join(again, ["kind", "norm"], "left").withColumn("attempt", F.when(F.col("more").isNull(), F.col("attempt")).when(F.lit(r < max_rounds - 1), F.col("attempt") + 1).otherwise(max_rounds + F.col("more"))).drop("more")
        out = now.filter("attempt > 0")
    raise AssertionError("unreachable")


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df has not."""
    while name.lower() in (c.lower() for c in df.columns):
        name += "_"
    return name


def replace(docs: DataFrame, key: str) -> DataFrame:
    """The rows of docs with entities in `text` replaced, and n_entities."""
    columns = [c for c in docs.columns if c != "n_entities"]
    found = common.materialise(entities(docs))
    changed = moved(found, key)
    attempt = lambda kind, norm: F.lit(0)
    if not changed.isEmpty():
        own, owner = fresh(docs, "_moved"), fresh(docs, "_owner")
        per_doc = found.join(changed, ["kind", "norm"]).select("doc_id", F.concat_ws("|", "kind", "norm").alias("k"), "attempt").distinct()
        maps = common.materialise(per_doc.groupBy(F.col("doc_id").alias(owner)).agg(F.map_from_entries(F.collect_list(F.struct("k", "attempt"))).alias(own)))
        docs = docs.join(maps, docs["doc_id"].eqNullSafe(maps[owner]), "left")
        attempt = lambda kind, norm: F.coalesce(F.element_at(own, F.concat_ws("|", kind, norm)), F.lit(0))

    def cased(word: Column, name: Column) -> Column:
        return F.when((word == F.upper(word)) & (F.length(word) > 2), F.upper(name)).otherwise(name)

    def person(raw: Column) -> Column:
        def one(words: Column) -> Column:
            return F.transform(F.arrays_zip(words.alias("w"), parts(raw).alias("p")), lambda x: cased(x["w"], surrogate(x["p"]["kind"], x["p"]["norm"], attempt(x["p"]["kind"], x["p"]["norm"]), key)))
        return F.concat(title_of(raw), F.array_join(common.let(name_words(raw), one), " "))

    def new(raw: Column) -> Column:
        def by_kind(kind: Column) -> Column:
            other = common.let(normal(kind, raw), lambda norm: laid_out(kind, raw, surrogate(kind, norm, attempt(kind, norm), key)))
            return F.when(kind.isNull(), raw).when(kind == "person", person(raw)).otherwise(other)
        return common.let(kind_of(raw), by_kind)

    raws, fresh_text, cut = fresh(docs, "_raw"), fresh(docs, "_text"), fresh(docs, "_cut")
    listed = docs.withColumn(cut, cut_up(F.col("text"))).withColumn(raws, F.col(f"{cut}.raw"))
    joined = F.array_join(F.zip_with(f"{cut}.between", F.transform(raws, new), lambda a, b: F.concat(a, F.coalesce(b, F.lit("")))), "")
    titled = F.array_distinct(F.filter(raws, lambda x: kind_of(x) == "person"))

    def recurring(text: Column, raw: Column) -> Column:
        """The names of one titled person elsewhere in the text: the family name, and given names before it."""
        def swap(acc: Column, words: Column) -> Column:
            names = F.split(F.regexp_replace(person(raw), r"^[^ ]+ ", ""), " ")
            family, new_family = F.element_at(words, -1), F.element_at(names, -1)
            mark = lambda w: F.concat(F.lit(r"(?<![\p{L}\p{N}])\Q"), w, F.lit(r"\E(?![\p{L}\p{N}])"))
            full = F.when(F.size(words) > 1, F.regexp_replace(acc, mark(F.array_join(words, " ")), F.array_join(names, " "))).otherwise(acc)
            return F.regexp_replace(full, mark(family), new_family)
        return common.let(name_words(raw), lambda words: swap(text, words))

    # The longest names first, so that a full name is found before its family name is gone.
    ordered = F.array_sort(titled, lambda a, b: F.length(b) - F.length(a))
    everywhere = F.when(F.size(titled) > 0, F.aggregate(ordered, F.col(fresh_text), recurring)).otherwise(F.col(fresh_text))
    counted = F.size(F.filter(raws, lambda x: kind_of(x).isNotNull()))
    listed = listed.withColumn(fresh_text, F.when(F.size(raws) > 0, joined).otherwise(F.col("text")))
    listed = listed.select(*[everywhere.alias("text") if c == "text" else F.col(f"`{c}`") for c in columns], F.when(F.size(raws) > 0, counted).otherwise(0).alias("n_entities"))
    return listed


def op9_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return replace(common.documents(spark, sf_dir).select("doc_id", "text"), DEMO_KEY)
