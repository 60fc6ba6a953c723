"""Surrogates for personal data: keyed, of one type and format, distinct, the same for the same entity everywhere.

Names are replaced piece by piece: a family name has one surrogate, a given name has one for each gender, and both maps
give different surrogates to different names. So a person keeps one identity under any title, with or without the given
name, and two people stay two. Pieces are learnt from mentions with a title; within that document the same pieces are
replaced without a title too.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import written

# fixed values
MALE_TITLES = ("Mr", "Herr", "Sr", r"M(?=\.)", "Monsieur", "Señor", "г-н")
FEMALE_TITLES = ("Mrs", "Ms", "Miss", "Frau", "Sra", "Mme", "Madame", "Señora", "г-жа")
OTHER_TITLES = ("Dr", "Prof")
PARTICLES = "van von der den de da di du del la le bin ibn al zu ter ten".split()
GIVEN = {
    "f": "alice berta clara diana elena flora greta helen irene julia karin laura maria nina olga paula".split(),
    "m": "adam bruno carl david erik felix georg henri ivan jonas kurt lukas martin nils oscar peter".split(),
    "n": "alex bobbie casey dana eden finley gray harper indigo jamie kim lee morgan noel parker robin".split(),
    "fc": "анна вера галина дарья елена зоя ирина ксения лидия мария нина ольга полина раиса софия юлия".split(),
    "mc": "антон борис виктор глеб денис егор захар иван кирилл лев максим николай олег павел роман степан".split(),
    "nc": "саша женя валя слава шура паша тоша лёша мика ника дина рика вита лана юля яша".split(),
}
GIVEN_ENDS = {"f": "na lia ra nne".split(), "m": "n rd s k".split(), "n": "ry lin ly ney".split(), "fc": "на лия ра лина".split(), "mc": "н р м слав".split(), "nc": "ня ша ля ка".split()}
FAMILY = {
    "": ("ash black brook clay east fair green hart holm kings lang marsh north stan wood west".split(), "berg born bury den field ford ham land ley man stone ton well wick worth mark".split()),
    "c": ("аза бел волк гром дуб еж жук зим кот лос мор нос орл пет рыб тит".split(), ["ов"]),
    "cs": ("аза бел волк гром дуб еж жук зим кот лос мор нос орл пет рыб тит".split(), ["ск", "цк"]),
    "cx": ("аза бел волк гром дуб еж жук зим кот лос мор нос орл пет рыб тит".split(), ["енко"]),
}
SOUNDS = {"": ("bdfghklmnprstvwz", "aeio"), "c": ("бвгджзклмнпрстфх", "аеио")}
#: Country codes of one and two digits; the others have three.
COUNTRY = r"^(1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|[0-9]{3})([0-9]*)$"

_PIECE = r"\p{Lu}[\p{L}\p{M}]+"
_WORD = rf"(?:[dDlLO]['’])?{_PIECE}(?:-{_PIECE})*"
_TITLES = "(?:" + "|".join(MALE_TITLES + FEMALE_TITLES + OTHER_TITLES) + r")\.? "
_NAME = rf"(?:\p{{Lu}}\. ?)*(?:(?:{'|'.join(PARTICLES)}) )*{_WORD}(?: (?:(?:{'|'.join(PARTICLES)}) )*{_WORD}){{0,2}}"
_HEX = "[0-9A-Fa-f]{1,4}"
#: Java patterns, in the order in which they are tried at a place.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+",
    "ip": r"(?<![0-9.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![0-9]|\.[0-9])",
    "ip6": rf"(?<![0-9A-Za-z:.])(?=[0-9A-Fa-f:]*[0-9])(?:(?:{_HEX}:){{7}}{_HEX}|(?=[0-9A-Fa-f]{{4}}:|{_HEX}:[0-9A-Fa-f])(?:{_HEX}:){{1,6}}(?::{_HEX}){{1,6}})(?![0-9A-Za-z:])",
    "secret": r"(?<![0-9A-Za-z])[0-9A-Fa-f]{32,64}(?![0-9A-Za-z])",
    "iban": r"(?<![0-9A-Za-z])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![0-9A-Za-z])",
    "phone": r"(?<![0-9A-Za-z+(.-])(?:\+[0-9]{1,3}[ .-]?(?:\([0-9]{2,4}\)|[0-9]{2,4})(?:[ .-]?[0-9]{2,4}){2,4}|\([0-9]{2,5}\)[ .-]?[0-9]{3,4}[ .-]?[0-9]{3,4}|0[0-9](?:[ .][0-9]{2}){4}|0[0-9]{1,4}[ .-][0-9]{3,4}[ .-][0-9]{3,4}|[0-9]{3}[.-][0-9]{3}[.-][0-9]{4})(?![0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "card": r"(?<![0-9.])[0-9]{4}(?:[ -]?[0-9]{4}){2}[ -]?[0-9]{1,7}(?![0-9])",
}
PLAIN = "|".join(PATTERNS.values())
TITLED = rf"(?<![\p{{L}}\p{{N}}])(?:{_TITLES})+{_NAME}"
CAPITAL = rf"(?<![\p{{L}}\p{{M}}]){_PIECE}"
#: From this attempt on, a surrogate of a fixed length gets longer with each.
LONGER_FROM = 8


def sql_array(words: list[str]) -> str:
    return "array(" + ", ".join(f"'{w}'" for w in words) + ")"


def kind_of(form: Column, other: str) -> Column:
    """The type of a matched string."""
    out = F.lit(other)
    for name in reversed(PATTERNS):
        out = F.when(form.rlike("^(?:" + PATTERNS[name] + ")$"), name).otherwise(out)
    return out


def normal(kind: Column, form: Column) -> Column:
    """What makes two forms one entity: the digits, for phones after the country code, or the lower case."""
    digits = F.regexp_replace(form, "[^0-9]", "")
    phone = F.when(form.startswith("+"), F.concat(F.lit("+"), F.regexp_replace(digits, COUNTRY, "$1|$2"))).otherwise(F.concat(F.lit("|"), digits))
    return F.when(kind == "phone", phone).when(kind.isin("card", "ssn"), digits).when(kind == "iban", F.replace(form, F.lit(" "), F.lit(""))).when(kind == "ip", form).otherwise(F.lower(form))


# --- names ------------------------------------------------------------------------------------------------------------


def with_stem(pieces: DataFrame, form: str) -> DataFrame:
    """Adds script, stem and ending of a piece of a name: Russian endings that tell the gender are left out of the stem."""
    low = F.lower(form)
    script = F.when(~low.rlike(r"\p{IsCyrillic}"), "").when(low.rlike("(?:ск|цк)(?:ий|ая)$"), "cs").when(low.rlike("(?:[оеё]в|[иы]н)а?$"), "c").otherwise("cx")
    ending = F.when(script == "cs", F.expr(f"right(lower(`{form}`), 2)")).when((script == "c") & low.endswith("а"), "а").otherwise("")
    d = pieces.withColumn("script", script).withColumn("ending", ending)
    return d.withColumn("stem", F.expr(f"substr(lower(`{form}`), 1, length(`{form}`) - length(ending))"))


def known_names(titled: DataFrame) -> DataFrame:
    """titled(pi_doc, pi_row, form) -> pi_doc, pi_row, stem and norm: role, gender, script and stem of each piece.

    A piece is a family name if it ends a mention of several words, else a given name if it stands before one, else a
    family name. Gender: what titles tell of this given name in the document, else of the family name it stands with,
    else what most titles of the corpus tell of the given name, else none.
    """
    title, name = F.regexp_extract("form", f"^(?:{_TITLES})+", 0), F.regexp_replace("form", f"^(?:{_TITLES})+", "")
    male, female = (title.rlike(r"(?:^| )(?:" + "|".join(t) + r")\.? ") for t in (MALE_TITLES, FEMALE_TITLES))
    d = titled.select("pi_doc", "pi_row", F.when(male, "m").when(female, "f").alias("g"), F.filter(F.split(name, " "), lambda w: w.rlike(_PIECE)).alias("w"))
    d = d.withColumn("family", F.lower(F.element_at("w", -1)))
    place = F.posexplode("w").alias("i", "word")
    each = d.select("pi_doc", "pi_row", "g", "family", F.size("w").alias("n"), place)
    each = each.select("*", F.explode(F.regexp_extract_all("word", F.lit(_PIECE), 0)).alias("piece"))
    each = with_stem(each.withColumn("role", F.when(F.col("i") < F.col("n") - 1, 1).when(F.col("n") > 1, 0).otherwise(2)), "piece")
    one = lambda c: F.when(F.min(c) == F.max(c), F.min(c))
    doc = ["pi_doc", "pi_row"]
    each = written(each, "name-pieces")
    families = each.groupBy(*doc, "family").agg(one("g").alias("g_family"))
    pieces = each.join(families, [*doc, "family"]).groupBy(*doc, "stem", "script").agg(F.min("role").alias("role"), one("g").alias("g_own"), F.count("g").alias("told"), one("g_family").alias("g_family"))
    corpus = each.filter("role = 1 AND g IS NOT NULL").groupBy("stem").agg(F.count_if(F.col("g") == "m").alias("m"), F.count_if(F.col("g") == "f").alias("f"))
    corpus = corpus.select("stem", F.when(F.col("m") > F.col("f"), "m").when(F.col("f") > F.col("m"), "f").alias("g_corpus"))
    gender = F.when(F.col("told") > 0, F.col("g_own")).otherwise(F.coalesce("g_family", "g_corpus"))
    d = pieces.join(corpus, "stem", "left").withColumn("g", F.when(F.col("role") == 1, F.coalesce(gender, F.lit("n"))).otherwise(""))
    role = F.when(F.col("role") == 1, "given").otherwise("family")
    # the same stem with and without a Russian ending is one name
    norm = F.concat_ws("|", role, "g", F.when(F.col("role") == 1, F.substring("script", 1, 1)).otherwise(F.col("script")), "stem")
    return d.groupBy(*doc, "stem").agg(F.min(norm).alias("norm"))


# --- surrogates -------------------------------------------------------------------------------------------------------


def candidate() -> str:
    """SQL for the surrogate of (kind, norm) at an attempt. h: 128 hexadecimal digits that key, type, entity and attempt
    give; dom: 64 that the key and what follows the @ give. Each attempt has more room than the one before, or does from
    LONGER_FROM on, so that every entity finds a place in the end."""
    digits = "translate(h, 'abcdef', '012345')"
    letters = "translate(h, '0123456789abcdef', 'bcdfghjklmnpqrst')"
    grown = f"greatest(0, attempt - {LONGER_FROM - 1})"
    shaped = "array_join(transform(sequence(1, length({x})), i -> CASE WHEN substr({x}, i, 1) RLIKE '[0-9]' THEN substr(%s, i, 1) WHEN substr({x}, i, 1) RLIKE '[a-z]' THEN substr(%s, i, 1) WHEN substr({x}, i, 1) RLIKE '[A-Z]' THEN upper(substr(%s, i, 1)) ELSE substr({x}, i, 1) END), '')" % (digits, letters, letters)
    hexed = "array_join(transform(sequence(1, length(norm)), i -> IF(substr(norm, i, 1) = ':', ':', IF(i = 1 OR substr(norm, i - 1, 1) = ':', translate(substr(h, i, 1), '0', 'f'), substr(h, i, 1)))), '')"
    number_at = lambda at, n, m: f"(CAST(conv(substr(h, {at}, {n}), 16, 10) AS INT) % {m})"
    payload = f"concat(substr(norm, 1, 1), substr({digits}, 1, length(norm) - 2 + {grown}))"
    # the digit at i counts twice if it is an odd number of places from the check digit
    luhn = f"aggregate(sequence(1, length({payload})), 0, (s, i) -> s + IF((length({payload}) + 1 - i) % 2 = 1, element_at(array(0, 2, 4, 6, 8, 1, 3, 5, 7, 9), CAST(substr({payload}, i, 1) AS INT) + 1), CAST(substr({payload}, i, 1) AS INT)))"
    bban = shaped.format(x="substr(norm, 5)")
    number = f"concat({bban}, substr(norm, 1, 2), '00')"
    mod97 = f"aggregate(transform(sequence(1, length({number})), i -> substr({number}, i, 1)), 0, (s, c) -> IF(c RLIKE '[0-9]', s * 10 + CAST(c AS INT), s * 100 + ascii(c) - 55) % 97)"
    part = lambda i: f"split(norm, '[|]')[{i}]"
    pick = lambda words, at: f"element_at({sql_array(words)}, {number_at(at, 4, len(words))} + 1)"
    sounds = lambda s: f"array_join(transform(slice(sequence(1, attempt + 1), 2, attempt), i -> concat(substr('{SOUNDS[s][0]}', {number_at('20 + i', 1, 16)} + 1, 1), substr('{SOUNDS[s][1]}', {number_at('70 + i', 1, 4)} + 1, 1))), '')"
    given = "CASE " + " ".join(f"WHEN concat({part(1)}, {part(2)}) = '{g}' THEN IF(attempt = 0, {pick(words, 1)}, concat({sounds(g[1:])}, {pick(GIVEN_ENDS[g], 5)}))" for g, words in GIVEN.items()) + " END"
    family = "CASE " + " ".join(f"WHEN {part(2)} = '{s}' THEN concat({pick(a, 9)}, {sounds(s[:1])}, {pick(b, 13)})" for s, (a, b) in FAMILY.items()) + " END"
    rest = "substring_index(norm, '|', -1)"
    return f"""CASE kind
        WHEN 'email' THEN concat({shaped.format(x="substring_index(norm, '@', 1)")}, substr(right({digits}, 40), 1, attempt), '@', translate(substr(dom, 1, 10), '0123456789abcdef', 'bcdfghjklmnpqrst'), '.example')
        WHEN 'ip' THEN concat(IF(attempt < 3, 10, 11 + {number_at(7, 2, 210)}), '.', {number_at(1, 2, 256)}, '.', {number_at(3, 2, 256)}, '.', {number_at(5, 2, 256)}, IF({grown} = 0, '', concat(':', substr({digits}, 20, {grown}))))
        WHEN 'ip6' THEN concat({hexed}, IF({grown} = 0, '', concat('%', substr(h, 60, {grown}))))
        WHEN 'secret' THEN substr(h, 1, length(norm))
        WHEN 'iban' THEN concat(substr(norm, 1, 2), lpad(CAST(98 - {mod97} AS STRING), 2, '0'), {bban})
        WHEN 'phone' THEN concat(substring_index(norm, '|', 1), '|', IF({rest} LIKE '0%', '0', ''), substr({digits}, 1, length({rest}) - IF({rest} LIKE '0%', 1, 0) + {grown}))
        WHEN 'ssn' THEN concat('9', substr({digits}, 1, 8 + {grown}))
        WHEN 'card' THEN concat({payload}, CAST((10 - {luhn} % 10) % 10 AS STRING))
        ELSE IF({part(0)} = 'given', {given}, {family}) END"""


def render() -> str:
    """SQL for the surrogate in the format of form: the same separators, capitals and endings."""
    flat = "replace(replace(sub, '+', ''), '|', '')"
    filled = "aggregate(sequence(1, length(form)), named_struct('t', '', 'n', 0), (s, i) -> IF(substr(form, i, 1) RLIKE '{c}', named_struct('t', concat(s.t, substr({s}, s.n + 1, 1)), 'n', s.n + 1), named_struct('t', concat(s.t, substr(form, i, 1)), 'n', s.n)))"
    numbers = filled.format(c="[0-9]", s=flat)
    cased = "array_join(transform(sequence(1, length(substring_index(sub, '@', 1))), i -> IF(substr(substring_index(form, '@', 1), i, 1) RLIKE '[A-Z]', upper(substr(sub, i, 1)), substr(sub, i, 1))), '')"
    domain = "substring_index(sub, '@', -1)"
    cased = f"concat({cased}, '@', CASE WHEN substring_index(form, '@', -1) RLIKE '^[A-Z][a-z]' THEN concat(upper(substr({domain}, 1, 1)), substr({domain}, 2)) WHEN substring_index(form, '@', -1) RLIKE '^[A-Z]' THEN upper({domain}) ELSE {domain} END)"
    name = "CASE WHEN upper(form) = form THEN upper(concat(sub, ending)) ELSE concat(upper(substr(sub, 1, 1)), substr(sub, 2), ending) END"
    return f"""CASE WHEN kind IN ('phone', 'card', 'ssn') THEN concat({numbers}.t, substr({flat}, {numbers}.n + 1))
        WHEN kind = 'iban' THEN {filled.format(c='[0-9A-Z]', s='sub')}.t
        WHEN kind IN ('secret', 'ip6') THEN IF(form RLIKE '[A-Z]' AND NOT form RLIKE '[a-z]', upper(sub), sub)
        WHEN kind = 'email' THEN {cased}
        WHEN kind = 'name' THEN {name}
        ELSE sub END"""


def assign(entities: DataFrame, key: str) -> DataFrame:
    """entities(kind, norm), distinct -> kind, norm, sub. sub is no entity of the table and stands for one entity alone.

    All entities try the surrogate of attempt 0. Of those that want one, the least gets it if it is nobody's own and not
    yet taken; the others try the next attempt, which has more room, until all have one. A round costs what is left.
    """
    value = F.when(F.col("kind") == "name", F.element_at(F.split("norm", "[|]"), -1)).otherwise(F.col("norm"))
    own = written(entities.select("kind", value.alias("sub")).distinct(), "originals")
    taken, left, attempt = None, entities, 0
    while True:
        h = F.concat(*[F.sha2(F.concat(F.lit(f"{key}|{half}|{attempt}|"), F.col("kind"), F.lit("|"), F.col("norm")), 256) for half in "ab"])
        dom = F.sha2(F.concat(F.lit(f"{key}|domain|"), F.substring_index("norm", "@", -1)), 256)
        tried = left.withColumns({"attempt": F.lit(attempt), "h": h, "dom": dom}).withColumn("sub", F.expr(candidate())).select("kind", "norm", "sub")
        tried = written(tried, "tried")
        # the least entity that wants a surrogate: its row's minimum, not a window, so a wanted one is no hot task
        least = tried.groupBy("kind", "sub").agg(F.min("norm").alias("first")).join(own, ["kind", "sub"], "left_anti")
        if taken is not None:
            least = least.join(taken.select("kind", "sub"), ["kind", "sub"], "left_anti")
        tried = written(tried.join(written(least, "least"), ["kind", "sub"], "left").select("kind", "norm", "sub", F.coalesce(F.col("first") == F.col("norm"), F.lit(False)).alias("ok")), "surrogates")
        done = tried.filter("ok").select("kind", "norm", "sub")
        taken = done if taken is None else taken.unionByName(done)
        left = tried.filter("NOT ok").select("kind", "norm")
        if left.isEmpty():
            return taken
        attempt += 1


def replace_entities(docs: DataFrame, key: str = "demo key") -> DataFrame:
    """docs, all columns, with surrogates in text; adds pi_found (how many strings were replaced).

    The key decides all surrogates: with one key an entity has one surrogate in the whole table and in each run over it,
    and two entities never share one. Names are those that stand behind a title somewhere in the document; single
    letters before a family name stay. Null text stays null, empty text empty; a table without entities comes back as
    it is, an empty one empty. Rows without a doc_id are replaced like others; equal rows get equal texts. Columns named
    pi_... are replaced. A long text is held once, with its matches. No Python runs on the executors.
    """
    docs = docs.drop(*[c for c in docs.columns if c.startswith("pi_")])
    doc = ["pi_doc", "pi_row"]
    rows = docs.withColumns({"pi_doc": F.coalesce(F.col("doc_id").cast("string"), F.lit("-")), "pi_row": F.xxhash64("text")})
    found = rows.select(*doc, F.posexplode(F.regexp_extract_all("text", F.lit(f"{PLAIN}|{TITLED}"), 0)).alias("at", "form"))
    found = written(found.withColumn("kind", kind_of(F.col("form"), "person")).distinct(), "entities")
    empty = found.select(*doc, "at", "form", "kind", normal(F.col("kind"), F.col("form")).alias("norm"), F.lit("").alias("ending"))
    titled = found.filter("kind = 'person'")
    people = None if titled.isEmpty() else written(titled.select(*doc).distinct(), "people")
    if people is None:
        each, pieces = empty, F.split("text", PLAIN, -1)
    else:
        names = written(known_names(titled), "names")
        again = rows.join(people, doc, "left_semi").select(*doc, F.posexplode(F.regexp_extract_all("text", F.lit(f"{PLAIN}|{CAPITAL}"), 0)).alias("at", "form"))
        again = with_stem(again.withColumn("kind", kind_of(F.col("form"), "name")).distinct(), "form")
        again = again.join(names.withColumnRenamed("norm", "name"), [*doc, "stem"], "left")
        norm = F.when(F.col("kind") == "name", F.col("name")).otherwise(normal(F.col("kind"), F.col("form")))
        each = empty.join(people, doc, "left_anti").unionByName(again.select(*doc, "at", "form", "kind", norm.alias("norm"), "ending"))
        each = written(each, "mentions")
        rows = rows.join(people.withColumn("pi_people", F.lit(True)), doc, "left")
        pieces = F.when(F.col("pi_people"), F.split("text", f"{PLAIN}|{CAPITAL}", -1)).otherwise(F.split("text", PLAIN, -1))
    subs = assign(each.select("kind", "norm").filter("norm IS NOT NULL").distinct(), key)
    shown = each.join(subs, ["kind", "norm"], "left").withColumn("new", F.when(F.col("sub").isNotNull(), F.expr(render())).otherwise(F.col("form")))
    listed = shown.groupBy(*doc).agg(F.sort_array(F.collect_list(F.struct("at", "new"))).alias("pi_new"), F.count("sub").alias("pi_n"))
    d = rows.join(listed, doc, "left").withColumn("pi_pieces", F.when(F.col("pi_n") > 0, pieces))
    text = F.coalesce(F.expr("array_join(zip_with(pi_pieces, pi_new, (p, e) -> concat(p, coalesce(e.new, ''))), '')"), F.col("text"))
    return d.select(*[text.alias(c) if c == "text" else F.col(f"`{c}`") for c in docs.columns], F.coalesce("pi_n", F.lit(0)).cast("long").alias("pi_found"))
