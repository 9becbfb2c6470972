"""Line-first quality rules in SQL functions only.

Every line is judged by three rules; lines that fail are removed, and a document that loses too much of its text is
rejected. Word counts and repeats of the whole text are measured beside them.

* punctuation: more than one mark of ``#*$%&<>`` for ten characters, or doubled exclamation marks on a third of the words
* navigation: three or more of the separators ``|»›•·→``, at least one for three words
* boilerplate: a phrase of PHRASES, which are those of four languages

Defined results: a null text counts as empty, has no words and is rejected; blank lines are dropped from the cleaned
text and count as nothing; a repeated doc_id is one more row; an empty table gives an empty result; other columns are
ignored. Nothing is shuffled, and repeats are found by sorting inside the row, so a long text costs n log n.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rangegate.llm.text import documents

#: Phrases of boilerplate lines, lower case (fixed values).
PHRASES = [
    *("licensed under", "released under", "all rights reserved", "terms of use", "terms of service", "privacy policy", "cookie policy", "accept cookies"),
    *("click here", "sign up for our", "subscribe to our", "enable javascript", "powered by", "skip to content", "back to top", "share on", "follow us on"),
    *("alle rechte vorbehalten", "datenschutzerklärung", "nutzungsbedingungen", "cookies akzeptieren"),
    *("tous droits réservés", "politique de confidentialité", "mentions légales", "accepter les cookies"),
    *("todos los derechos reservados", "política de privacidad", "términos de uso", "aceptar cookies"),
]
#: Marks between the entries of a navigation line (fixed values).
SEPARATORS = "|»›•·→"
BLANKS = " \\t\\n\\u000b\\u000c\\r"
MIN_WORDS = 50
MAX_REPEAT_PERCENT = 50
MIN_KEPT_PERCENT = 60


def let(value: str, name: str, body: str) -> str:
    """SQL that computes ``value`` once a row and names it inside ``body``."""
    return f"transform(array({value}), {name} -> {body})[0]"


def words(text: str) -> str:
    return f"filter(split({text}, '[\\\\x20\\\\x09-\\\\x0D]+', -1), w -> w <> '')"


def marks(text: str, chars: str) -> str:
    return f"cast(char_length({text}) - char_length(translate({text}, '{chars}', '')) as bigint)"


def repeat_words(ws: str) -> str:
    """Number of words inside three-word windows that stand twice or more in the word array ``ws``."""
    gram = f"concat_ws(' ', {ws}[i], {ws}[i + 1], {ws}[i + 2])"
    hashes = f"transform(sequence(0, size({ws}) - 3), i -> xxhash64({ws}[i], {ws}[i + 1], {ws}[i + 2]))"
    rows = f"array_sort(transform(hs, (h, i) -> struct(h as h, {gram} as g, i as i)))"
    twice = "filter(transform(st, (x, j) -> if((j > 0 and st[greatest(j - 1, 0)].g = x.g) or (j < size(st) - 1 and st[least(j + 1, size(st) - 1)].g = x.g), x.i, -1)), p -> p >= 0)"
    covered = "aggregate(array_sort(ps), struct(cast(0 as int) as reach, cast(0 as bigint) as n), (a, p) -> struct(cast(p + 3 as int) as reach, a.n + p + 3 - greatest(p, a.reach) as n), a -> a.n)"
    found = let(rows, "st", let(twice, "ps", covered))
    return f"if(size({ws}) < 4, cast(0 as bigint), {let(hashes, 'hs', f'if(size(array_distinct(hs)) = size(hs), cast(0 as bigint), {found})')})"


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, t, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    lines = "filter(split(t, '\\n', -1), l -> l rlike '[^\\\\x20\\\\x09-\\\\x0D]')"
    found = let(words("t"), "ws", f"struct(cast(size(ws) as bigint) as n_words, {repeat_words('ws')} as n_repeat_words)")
    base = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("t")).withColumn("m", F.expr(found))
    return base.select(
        "doc_id",
        "t",
        "m.n_words",
        F.expr(f"cast(char_length(translate(t, '{BLANKS}', '')) as bigint)").alias("word_chars"),
        F.expr(marks("t", "#*$%&|<>")).alias("n_symbols"),
        F.expr(let(lines, "ls", "cast(size(ls) - size(array_distinct(ls)) as bigint)")).alias("n_dup_lines"),
        "m.n_repeat_words",
    )


def line_passes(line: str) -> str:
    """SQL condition of a line that no rule removes."""
    n_words = f"size(split(trim({line}), ' +'))"
    punctuation = f"10 * {marks(line, '#*$%&<>')} > char_length({line}) or 3 * {marks(line, '!')} > 2 * {n_words} and instr({line}, '!!') > 0"
    navigation = f"{marks(line, SEPARATORS)} >= 3 and 3 * {marks(line, SEPARATORS)} >= {n_words}"
    return f"not ({punctuation} or {navigation} or lower({line}) rlike '{'|'.join(PHRASES)}')"


def apply_line_rules(docs: DataFrame) -> DataFrame:
    """All measures with base_failed, cleaned, kept_chars and kept."""
    m = measured(docs)
    cleaned = f"array_join(filter(split(t, '\\n', -1), l -> l rlike '[^\\\\x20\\\\x09-\\\\x0D]' and {line_passes('l')}), '\\n')"
    m = m.withColumn("base_failed", F.expr(f"n_words < {MIN_WORDS} or 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words"))
    m = m.withColumn("cleaned", F.expr(cleaned)).withColumn("kept_chars", F.expr(f"cast(char_length(translate(cleaned, '{BLANKS}', '')) as bigint)"))
    return m.withColumn("kept", F.expr(f"not base_failed and 100 * kept_chars >= {MIN_KEPT_PERCENT} * word_chars")).drop("t")


def op1_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return apply_line_rules(documents(spark, sf_dir)).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept_chars", "kept")


def oracle() -> str:
    blanks = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
    count = lambda x, chars: f"(length({x}) - length(translate({x}, '{chars}', '')))"
    line = f"""not (10 * {count('l', '#*$%&<>')} > length(l)
      or 3 * {count('l', '!')} > 2 * len(regexp_split_to_array(trim(l), ' +')) and contains(l, '!!')
      or {count('l', SEPARATORS)} >= 3 and 3 * {count('l', SEPARATORS)} >= len(regexp_split_to_array(trim(l), ' +'))
      or {' or '.join(f"contains(lower(l), '{p}')" for p in PHRASES)})"""
    return f"""
with d as (
  select doc_id, coalesce(text, '') as t, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as ws,
    list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: length(translate(x, {blanks}, '')) > 0) as ls from documents
), win as (
  select doc_id, i, ws[i:i+2] as g from d, unnest(range(1, len(ws) - 1)) as r(i)
), rep as (
  select doc_id, i from (select doc_id, i, count(*) over (partition by doc_id, g) as c from win) where c > 1
), cov as (
  select doc_id, count(distinct i + k) as n from rep, range(0, 3) as r(k) group by doc_id
), kept as (
  select doc_id, sum(length(translate(l, {blanks}, ''))) as n from (select doc_id, unnest(ls) as l from d) where {line} group by doc_id
), m as (
  select d.doc_id, len(ws)::bigint as n_words, length(translate(t, {blanks}, ''))::bigint as word_chars, {count('t', '#*$%&|<>')}::bigint as n_symbols,
    (len(ls) - len(list_distinct(ls)))::bigint as n_dup_lines, coalesce(cov.n, 0)::bigint as n_repeat_words, coalesce(kept.n, 0)::bigint as kept_chars
  from d left join cov using (doc_id) left join kept using (doc_id)
), b as (select *, n_words < {MIN_WORDS} or 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words as base_failed from m)
select *, not base_failed and 100 * kept_chars >= {MIN_KEPT_PERCENT} * word_chars as kept from b
"""


OP1_SQL = oracle()
