r"""PII surrogates: detected entities get keyed, type-consistent replacements.  DataFrame functions only.

One alternation finds all entities of a text; ``split`` on the same pattern gives what stands between them.
An entity falls into parts (an e-mail address, a number, or the given name and the surname of a titled name).
A titled name's words get their surrogates also where they stand alone in the same text, so a person keeps
one name there.  A part's canonical form (lower case; numbers without separators) is hashed with a secret key, and the hash
fills the form character by character: digits give digits, letters give letters of the same script and
case, separators, country codes, card brand, titles and top-level domains stay, a valid card checksum
stays valid.  Given names follow the gender of the title.  Equal canonical forms get equal surrogates in all
documents (coreference).

Collision check: a surrogate that two parts of a kind share, or that is itself a part found in the corpus,
is hashed again with the next attempt number, for all but the first holder; from attempt ``WIDEN`` on a digest suffix is
added so that the search ends even where a form has too few surrogates.

Rows shuffled: distinct entities and their places (keyed by a digest of the text, copies once) and the texts
that hold entities; texts without entities pass through.  Hot entities or texts meet one-row-per-key tables
by joins that AQE splits.

Defined cases: null text stays null; texts without entities stay as they are; repeated rows are returned as
often as they come; extra columns of any name pass through; an empty table gives no rows.

The key is an argument, or the session setting ``KEY_SETTING``; where neither is given, a random one is drawn that
lasts as long as the driver's process.
"""

from __future__ import annotations

import secrets

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import StoredChain, stored, table, unused_names

KEY_SETTING = "spark.querygrade.surrogate.key"
_DRAWN = secrets.token_hex(32)
WIDEN = 6
MAX_ATTEMPTS = 40

# fixed values: patterns of the kinds, in the order in which they are tried
_L = r"\p{L}\p{M}"
PATTERNS = {
    "email": rf"(?<![{_L}\p{{N}}._%+\-])[{_L}\p{{N}}._%+\-]++@[{_L}\p{{N}}\-]+(?:\.[{_L}\p{{N}}\-]+)*\.[{_L}]{{2,24}}",
    "api_key": r"\b(?:AKIA|ASIA)[0-9A-Z]{16}\b|\b(?:ghp|gho|ghs|glpat|xox[abp]|sk|pk)[_\-][0-9A-Za-z\-_]{16,80}",
    "secret": r"\b(?:[0-9a-f]{32,128}|[0-9A-F]{32,128})\b",
    "iban": r"\b[A-Z]{2}[0-9]{2}(?: ?[0-9A-Z]{4}){3,7}(?: ?[0-9A-Z]{1,3})?\b",
    "ipv6": r"\b(?:[0-9A-Fa-f]{1,4}:){7}[0-9A-Fa-f]{1,4}\b",
    "ipv4": r"(?<![\p{L}0-9._])(?:(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])\.){3}(?:25[0-5]|2[0-4][0-9]|1?[0-9]?[0-9])(?![0-9]|\.[0-9])",
    "phone": r"(?<![0-9+])\+[0-9]{1,3}[ .\-]?(?:\([0-9]{1,4}\)[ .\-]?)?[0-9]{2,4}(?:[ .\-]?[0-9]{2,4}){1,4}(?![0-9])|(?<![0-9])\([0-9]{3}\) ?[0-9]{3}[ .\-][0-9]{4}(?![0-9])|(?<![0-9\-.])[0-9]{3}[.\-][0-9]{3}[.\-][0-9]{4}(?![0-9\-.])",
    "ssn": r"(?<![0-9\-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9\-])",
    "card": r"(?<![0-9])[0-9](?:[ \-]?[0-9]){12,18}(?![0-9])",
    "name": rf"\b(?=[MSLDPHFГ])(?:Mr|Mrs|Ms|Miss|Sir|Lady|Dr|Prof|Herr|Frau|Monsieur|Madame|Mme|Señor|Señora|Sr|Sra|Г-н|Г-жа)\.? \p{{Lu}}[{_L}'’\-]+(?: \p{{Lu}}[{_L}'’\-]+)?",
}
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
#: Every text with an entity matches this cheaper pattern.
HINT = r"@|[0-9][0-9]|[0-9][. \-:][0-9]|[0-9A-Fa-f]:[0-9A-Fa-f]|[0-9A-Fa-f]{32}|\b(?:AKIA|ASIA)[0-9A-Z]|\b(?:ghp|gho|ghs|glpat|xox[abp]|sk|pk)[_\-]|\b(?=[MSLDPHFГ])(?:Mrs?|Ms|Miss|Sir|Lady|Dr|Prof|Herr|Frau|Monsieur|Madame|Mme|Señora?|Sra?|Г-н|Г-жа)\.? \p{Lu}"
MALE = r"^(Mr|Sir|Herr|Monsieur|Señor|Sr|Г-н)\b"
FEMALE = r"^(Mrs|Ms|Miss|Lady|Frau|Madame|Mme|Señora|Sra|Г-жа)\b"
# fixed values: given names by gender, and letters of each script that the sixteen hex digits stand for
GIVEN = {
    "given_m": "Adam Bruno Carl David Emil Felix Georg Hugo Ivan Jonas Karl Leon Marco Niklas Otto Paul".split(),
    "given_f": "Anna Berta Clara Diana Elena Flora Greta Hanna Irene Julia Klara Laura Maria Nora Olga Paula".split(),
    "given_n": "Alex Robin Kim Noel Sasha Charlie Dana Jules Luca Mika Nikita Quinn Remy Toni Ulli Yuri".split(),
}
HEX = "0123456789abcdef"
LETTERS = {
    r"[\p{IsLatin}]": "aeioubdfglmnprst",
    r"[\p{IsCyrillic}]": "авекмнорстудилпб",
    r"[\p{IsGreek}]": "αεηικλμνοπρστυφω",
    r"[\p{IsHan}]": "山川田中林木水火石金花月日雨雪风",
}
VOWELS, CONSONANTS = "aeioaeiouaeioaei", "bdfgklmnprstvzhj"


def secret_key(spark: SparkSession, key: str | None = None) -> str:
    return key or spark.conf.get(KEY_SETTING, None) or _DRAWN


def entities(text: Column) -> Column:
    return F.regexp_extract_all(text, F.lit(ANY), F.lit(0))


def kind_of(entity: Column) -> Column:
    out = F.lit(None).cast("string")
    for kind, pattern in reversed(PATTERNS.items()):
        out = F.when(entity.rlike(f"^(?:{pattern})$"), F.lit(kind)).otherwise(out)
    return out


def _digest(kind: Column, canonical: Column, attempt: Column, key: str) -> Column:
    return F.sha2(F.concat_ws("|", F.lit(key), kind, canonical, attempt.cast("string")), 256)


def _letter(char: Column, hexed: Column) -> Column:
    out = F.translate(hexed, HEX, LETTERS[r"[\p{IsLatin}]"])
    for script, letters in LETTERS.items():
        out = F.when(char.rlike(script), F.translate(hexed, HEX, letters)).otherwise(out)
    return F.when(F.upper(char) == char, F.upper(out)).otherwise(out)


def _filled(form: Column, stream: Column, keep: Column) -> Column:
    """``form`` with characters after the first ``keep`` replaced within their class by the stream's hex digits."""

    def one(at: Column) -> Column:
        char, hexed = F.substring(form, at, 1), F.substring(stream, (at - 1) % 64 + 1, 1)
        return F.when(at <= keep, char).when(char.rlike("[0-9]"), F.translate(hexed, HEX, "0123456789371950")).when(char.rlike(r"\p{L}"), _letter(char, hexed)).otherwise(char)

    return F.when(F.length(form) > 0, F.array_join(F.transform(F.sequence(F.lit(1), F.length(form)), one), "")).otherwise(form)


def _luhn(digits: Column) -> Column:
    """Sum of the Luhn rule modulo 10 (0: valid)."""
    backwards = F.reverse(digits)

    def one(at: Column) -> Column:
        d = F.substring(backwards, at, 1).cast("int")
        twice = d * 2
        return F.when(at % 2 == 1, d).otherwise(F.when(twice > 9, twice - 9).otherwise(twice))

    return F.aggregate(F.transform(F.sequence(F.lit(1), F.length(digits)), one), F.lit(0), lambda a, x: a + x) % 10


def _syllables(stream: Column, n: int) -> Column:
    parts = [F.translate(F.substring(stream, 9 + k, 1), HEX, CONSONANTS if k % 2 == 0 else VOWELS) for k in range(2 * n)]
    return F.initcap(F.concat(*parts))


def with_surrogates(parts: DataFrame, key: str) -> DataFrame:
    """``parts(kind, canonical, attempt)`` with their surrogates; built in columns that each are computed once."""
    kind, canonical, attempt, stream, filled = (F.col(c) for c in ("kind", "canonical", "attempt", "stream", "filled"))
    named = kind.isin("surname", *GIVEN)
    phone_at = F.instr(canonical, "|")
    keep = F.when(kind == "card", 1).when(kind == "iban", 2).when(kind == "api_key", 4).when(kind == "phone", phone_at).otherwise(0)
    form = F.when(kind == "email", F.split_part(canonical, F.lit("@"), F.lit(1))).otherwise(canonical)
    domain = F.split_part(canonical, F.lit("@"), F.lit(2))
    host, tld = F.regexp_extract(domain, r"^(.*)(\.[^.]+)$", 1), F.regexp_extract(domain, r"^(.*)(\.[^.]+)$", 2)
    octets = F.concat_ws(".", *[(F.conv(F.substring(stream, 1 + 4 * k, 4), 16, 10).cast("int") % 254 + 1).cast("string") for k in range(4)])
    hexed = F.substring(F.rpad(F.concat(stream, F.sha2(stream, 256)), 128, "0"), F.lit(1), F.length(canonical))
    pick = F.conv(F.substring(stream, 1, 4), 16, 10).cast("int") % 16 + 1
    given = F.lit(None).cast("string")
    for who, names in GIVEN.items():
        given = F.when(kind == who, F.element_at(F.array(*map(F.lit, names)), pick)).otherwise(given)
    body = F.regexp_replace(filled, ".$", "")
    card = F.when(_luhn(canonical) == 0, F.concat(body, ((F.lit(10) - _luhn(F.concat(body, F.lit("0")))) % 10).cast("string"))).otherwise(filled)
    latin = canonical.rlike(r"\p{IsLatin}")
    spoken = F.when(kind == "surname", _syllables(stream, 4)).when(attempt < 3, given).otherwise(_syllables(stream, 3))
    plain = F.when(kind == "ipv4", octets).when(kind.isin("secret", "ipv6"), hexed).when(kind == "card", card).when(named & latin, spoken).when(named, F.initcap(filled)).otherwise(filled)
    suffix = F.when(attempt >= WIDEN, F.when(named, _syllables(stream, 2)).otherwise(F.translate(F.substring(stream, 33, 6), HEX, "0123456789371950"))).otherwise("")
    out = F.when(kind == "email", F.concat(F.col("plain"), suffix, F.lit("@"), F.col("host"), F.col("tld"))).when(named, F.concat(F.col("plain"), suffix)).otherwise(F.col("plain"))
    return (
        parts.withColumn("stream", _digest(kind, canonical, attempt, key))
        .withColumn("filled", F.when(kind.isin("secret", "ipv4", "ipv6"), canonical).otherwise(_filled(form, stream, keep)))
        .withColumn("host", F.when(kind == "email", _filled(host, _digest(F.lit("domain"), domain, F.lit(0), key), F.lit(0))))
        .withColumns({"tld": tld, "plain": plain})
        .withColumn("surrogate", out)
        .select("kind", "canonical", "attempt", "surrogate")
    )


def parts_of(entity: Column, kind: Column) -> Column:
    """array<struct<kind, canonical>> of an entity."""
    low = F.lower(entity)
    bare = F.regexp_replace(low, r"[^\p{L}\p{N}]", "")
    country = F.regexp_extract(entity, r"^\+([0-9]{1,3})(?![0-9])", 1)
    phone = F.concat(country, F.lit("|"), F.substring(bare, F.length(country) + 1, F.length(bare)))
    canonical = F.when(kind.isin("email", "ipv4"), low).when(kind == "phone", phone).when(kind == "api_key", entity).otherwise(bare)
    words = F.split(entity, " ")
    gender = F.when(entity.rlike(MALE), "given_m").when(entity.rlike(FEMALE), "given_f").otherwise("given_n")
    surname = F.struct(F.lit("surname").alias("kind"), F.lower(F.element_at(words, -1)).alias("canonical"))
    named = F.when(F.size(words) > 2, F.array(F.struct(gender.alias("kind"), F.lower(F.element_at(words, 2)).alias("canonical")), surname)).otherwise(F.array(surname))
    return F.when(kind == "name", named).otherwise(F.array(F.struct(kind.alias("kind"), canonical.alias("canonical"))))


def _laid_out(entity: Column, filled: Column, own_case: Column) -> Column:
    """Letters and digits of ``filled`` in the layout of ``entity``, and in its case where ``own_case`` holds."""

    def one(at: Column) -> Column:
        char = F.substring(entity, at, 1)
        rank = F.length(F.regexp_replace(F.substring(entity, F.lit(1), at), r"[^\p{L}\p{N}]", ""))
        put = F.substring(filled, rank, 1)
        cased = F.when(~own_case, put).when((F.upper(char) == char) & char.rlike(r"\p{L}"), F.upper(put)).otherwise(put)
        return F.when(char.rlike(r"[\p{L}\p{N}]"), cased).otherwise(char)

    return F.array_join(F.transform(F.sequence(F.lit(1), F.length(entity)), one), "")


def assembled(entity: Column, kind: Column, given: Column, last: Column) -> Column:
    """The entity's surrogate from the surrogates of its parts."""
    title = F.split_part(entity, F.lit(" "), F.lit(1))
    name = F.concat_ws(" ", title, given, last)
    mail = F.when(F.upper(entity) == entity, F.upper(last)).otherwise(last)
    hexed = kind.isin("secret", "ipv6")  # digits and letters swap places there, so the case is one for all
    laid = _laid_out(entity, F.regexp_replace(last, r"\|", ""), ~hexed)
    laid = F.when(hexed & (F.upper(entity) == entity), F.upper(laid)).otherwise(laid)
    return F.when(kind == "name", name).when(kind == "email", mail).when(kind.isin("ipv4", "api_key"), last).otherwise(laid)


def _dealt(df: DataFrame, *keys: str) -> DataFrame:
    """Few bytes but much work for each row: keep as many tasks as the session's shuffles have."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *keys)


def distinct_surrogates(parts: DataFrame, key: str) -> DataFrame:
    """kind, canonical, surrogate for distinct ``parts(kind, canonical)``; surrogates of a kind are distinct and new."""
    chain = StoredChain(parts.sparkSession, "surrogates")
    now = chain.put(with_surrogates(_dealt(parts, "kind", "canonical").select("kind", "canonical", F.lit(0).alias("attempt")), key))
    for _ in range(MAX_ATTEMPTS):
        low = F.lower("surrogate").alias("low")
        held = now.groupBy("kind", low).agg(F.count(F.lit(1)).alias("n"), F.min(F.struct((-F.col("attempt")).alias("settled"), "canonical")).getField("canonical").alias("holder")).where("n > 1").select("kind", "low", "holder")
        taken = now.select("kind", F.col("canonical").alias("low"), F.lit(True).alias("real"))
        marked = now.withColumn("low", F.lower("surrogate")).join(held, ["kind", "low"], "left").join(taken, ["kind", "low"], "left")
        again = F.col("real").isNotNull() | (F.col("holder").isNotNull() & (F.col("holder") != F.col("canonical")))
        marked = stored(marked.select("kind", "canonical", "attempt", "surrogate", again.alias("again")), "surrogate-check")
        if marked.where("again").isEmpty():
            break
        anew = with_surrogates(marked.where("again").select("kind", "canonical", (F.col("attempt") + 1).alias("attempt")), key)
        now = chain.put(marked.where(~F.col("again")).drop("again").unionByName(anew))
    else:
        raise RuntimeError("surrogates of some kind are exhausted")
    return now.select("kind", "canonical", "surrogate")


def surrogate_table(docs: DataFrame, key: str) -> tuple[DataFrame, DataFrame]:
    """(places(text_key, pos, entity), names(entity, kind, surrogate)) of all texts."""
    found = docs.where(F.col("text").rlike(HINT)).select(F.md5(F.col("text").cast("binary")).alias("text_key"), entities(F.col("text")).alias("e"))
    places = stored(found.groupBy("text_key").agg(F.first("e").alias("e")).select("text_key", F.posexplode("e").alias("pos", "entity")), "pii-places")
    kinds = _dealt(places.select("entity").distinct(), "entity").withColumn("of", kind_of(F.col("entity")))
    parts = stored(kinds.withColumn("parts", parts_of(F.col("entity"), F.col("of"))).select("entity", "of", F.posexplode("parts").alias("part", "p")).select("entity", "of", "part", "p.kind", "p.canonical"), "pii-parts")
    chosen = distinct_surrogates(parts.select("kind", "canonical").distinct(), key)
    whole = parts.join(chosen, ["kind", "canonical"]).groupBy("entity", "of").agg(F.max(F.when(F.col("kind").startswith("given"), F.col("surrogate"))).alias("given"), F.max(F.when(~F.col("kind").startswith("given"), F.col("surrogate"))).alias("last"))
    return places, stored(_dealt(whole, "entity").select("entity", F.col("of").alias("kind"), assembled(F.col("entity"), F.col("of"), F.col("given"), F.col("last")).alias("surrogate")), "pii-surrogates")


def _mentions(put: Column) -> Column:
    """array<struct<word, put>>: the words of the titled names of a text and their surrogates."""

    def words(e: Column) -> Column:
        old, new = F.split(e["entity"], " "), F.split(e["surrogate"], " ")
        return F.arrays_zip(F.slice(old, 2, F.size(old)).alias("word"), F.slice(new, 2, F.size(new)).alias("put"))

    return F.array_distinct(F.flatten(F.transform(F.filter(put, lambda e: e["kind"] == "name"), words)))


def _named_alike(gap: Column, mentions: Column) -> Column:
    """What stands between entities, with the words of ``mentions`` replaced."""
    edge = rf"[{_L}\p{{N}}]"
    one = lambda text, m: F.regexp_replace(text, F.concat(F.lit(rf"(?<!{edge})\Q"), m["word"], F.lit(rf"\E(?!{edge})")), m["put"])
    return F.when(F.size(mentions) == 0, gap).otherwise(F.aggregate(mentions, gap, one))


def pseudonymize(docs: DataFrame, key: str | None = None) -> DataFrame:
    """``docs`` with surrogates in ``text``, and a last column ``n_entities`` (underscores before it where ``docs`` has one)."""
    places, names = surrogate_table(docs, secret_key(docs.sparkSession, key))
    text_key, put, mentions, count = unused_names(docs.columns, "text_key", "put", "mentions", "n_entities")
    struct = F.struct("pos", "surrogate", "kind", F.when(F.col("kind") == "name", F.col("entity")).alias("entity"))
    filled = places.join(names, "entity").groupBy("text_key").agg(F.sort_array(F.collect_list(struct)).alias(put)).withColumnRenamed("text_key", text_key)
    columns = [F.col(f"`{c}`") for c in docs.columns]
    hinted = F.coalesce(F.col("text").rlike(HINT), F.lit(False))
    met = docs.where(hinted).withColumn(text_key, F.md5(F.col("text").cast("binary"))).join(filled, text_key, "left")
    met = met.withColumn(mentions, _mentions(F.col(put)))
    woven = F.zip_with(F.split(F.col("text"), ANY, -1), F.col(f"{put}.surrogate"), lambda gap, s: F.concat(_named_alike(gap, F.col(mentions)), F.coalesce(s, F.lit(""))))
    changed = met.withColumn("text", F.when(F.col(put).isNull(), F.col("text")).otherwise(F.array_join(woven, "")))
    changed = changed.withColumn(count, F.when(F.col(put).isNull(), 0).otherwise(F.size(put)).cast("long"))
    return changed.select(*columns, count).unionByName(docs.where(~hinted).withColumn(count, F.lit(0).cast("long")))


def op3_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pseudonymize(table(spark, sf_dir, "documents")).select("doc_id", "text", "n_entities")
