"""Benchmark decontamination by template windows.

Texts and benchmark items are canonicalised alike: numbers (with decimals and separators), names (runs of capitalised
words, at sentence starts unless the word is a common one) and units after a number become typed placeholders, one
token each, everything else lower-case words. Windows of `WINDOW` adjacent
tokens are hashed and joined, so a question asked again with other numbers or names still meets its template. Matches
of one text and item are gathered by their offset (one offset is one occurrence). An occurrence counts if it covers
enough of the item's windows and its slots are consistent: within it, one value of the item always became the same
value of the text.

All steps are DataFrame expressions. The windows of the benchmark are broadcast only if counted to be at most
`MAX_BROADCAST`; else the join shuffles. Texts are scanned once, and only matches leave the map side.

Defined cases: null and empty texts are clean; items of fewer than WINDOW tokens match nothing, nor do windows of
placeholders only; a window that several items share counts for each; repeated rows are one document (its matches are
counted once); of items that share an id one is taken; very long texts are read whole; of several items found the
smallest id is named; an empty benchmark leaves all texts clean, an empty table of documents gives an empty result;
further columns, whatever their names, are ignored by `contaminated`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from relcodec.llm import common

WINDOW = 8
#: An occurrence needs this many windows, or half of the item's if that is less.
ENOUGH = 6
MAX_BROADCAST = 1_000_000
NAME, NUMBER, UNIT = "zznamezz", "zznumzz", "zzunitzz"
#: Units after a number.
UNITS = "km|kg|cm|mm|m|g|l|ml|h|min|s|percent|miles|mile|hours|hour|minutes|days|years|dollars|dollar|euros|euro|cents"
#: Words that are no names where a sentence starts (elsewhere every capitalised word is one).
COMMON = ("a|about|after|all|also|although|an|and|another|any|are|as|at|because|before|both|but|by|calculate|can|compute|consider|could|did|do|does|during|each|either|estimate|every|explain|find|first|for|from|"
          "given|had|has|have|he|her|here|his|how|however|if|in|into|is|it|its|last|later|let|many|may|more|most|my|next|no|not|now|of|on|once|one|or|our|out|over|question|she|should|show|since|so|solve|some|"
          "suppose|than|that|the|their|then|there|these|they|this|those|through|to|today|tomorrow|two|under|until|up|was|we|were|what|when|where|which|while|who|whose|why|will|with|would|yesterday|yet|you|your|"
          "aber|als|am|auf|aus|bei|beim|das|dem|den|der|des|die|dies|diese|dieser|doch|durch|ein|eine|einem|einen|einer|er|es|für|hat|ich|ihr|ihre|im|ist|mit|nach|nicht|noch|nun|nur|oder|sein|seine|seit|sich|sie|sind|"
          "so|um|und|unter|von|vor|wann|war|warum|was|welche|wenn|wer|wie|wieviel|wir|wird|wo|zu|zum|zur|"
          "au|aux|avec|ce|ces|cette|chaque|combien|comment|dans|de|du|elle|elles|en|est|et|il|ils|je|la|le|les|leur|lorsque|mais|ne|nous|on|ou|où|par|pas|pour|pourquoi|puis|quand|que|quel|quelle|qui|sa|ses|si|son|"
          "sont|sur|un|une|vous|al|como|con|cuando|cuál|cuántas|cuántos|del|donde|dónde|el|ella|ellas|ellos|entonces|era|es|esta|este|está|las|los|más|muy|no|nos|para|pero|por|porque|pues|qué|se|sin|su|sus|también|una|y")
#: Marks inside canonical text: around every word of a name, and within a token in place of what would part it.
_EDGE, _WITHIN = "\x01", "\x02"
_STARTERS = "|".join(sorted({w[0].upper() + w[1:] for w in COMMON.split("|") if len(w) > 1}))
_NAME_WORD = (r"(?=\p{Lu})(?<![\p{L}\p{N}])(?:(?<=[\p{Ll},;] )|(?!(?:" + _STARTERS + r")(?![\p{L}\p{N}])))"
              r"(?:(?:\p{Lu}\p{Ll}+)+(?![\p{L}\p{N}])|\p{Lu}(?=['\u2019]\p{Lu}\p{Ll}))")
_PARTS = r"[^\p{L}\p{N}\x02]+"


def canonical(text: Column) -> Column:
    """Text whose numbers are one token each, decimals and separators included (thousands lose their commas, so 1,200
    is 1200), and whose names are marked: a run of capitalised words, hyphens and apostrophes between them, is one."""
    plain = F.translate(F.coalesce(text, F.lit("")), _EDGE + _WITHIN, "  ")
    numbers = F.regexp_replace(F.regexp_replace(plain, r"(?<=\p{N}),(?=\p{N}{3}(?!\p{N}))", ""), r"(?<=\p{N})[.,](?=\p{N})", _WITHIN)
    marked = F.regexp_replace(numbers, _NAME_WORD, f"{_EDGE}$0{_EDGE}")
    return F.regexp_replace(marked, f"{_EDGE}[ '\u2019-]{_EDGE}", _WITHIN)


def raw_tokens(canon: Column) -> Column:
    return F.split(F.trim(F.regexp_replace(F.lower(F.translate(canon, _EDGE, "")), _PARTS, " ")), " ")


def template_tokens(canon: Column) -> Column:
    """As many tokens as raw_tokens, with placeholders for what a question may vary."""
    named = F.regexp_replace(canon, f"{_EDGE}[^{_EDGE}]+{_EDGE}", NAME)
    words = F.trim(F.regexp_replace(F.lower(named), _PARTS, " "))
    counted = F.regexp_replace(words, r"\p{N}[\p{N}\x02]*", NUMBER)
    return F.split(F.trim(F.regexp_replace(F.concat(counted, F.lit(" ")), f"{NUMBER} ({UNITS}) ", f"{NUMBER} {UNIT} ")), " ")


def tokens(table: DataFrame, keys: list[str], text: str) -> DataFrame:
    """keys, cut (raw and template tokens)."""
    cut = common.let(canonical(F.col(text)), lambda c: F.struct(raw_tokens(c).alias("raw"), template_tokens(c).alias("template")))
    # Exploded, so that no later projection computes it again.
    return table.select(*keys, F.explode(F.array(cut)).alias("cut"))


def windows(table: DataFrame, keys: list[str], text: str) -> DataFrame:
    """keys, at, h: a row per window, without its tokens."""
    return tokens(table, keys, text).select(*keys, F.posexplode(common.window_hashes(F.col("cut.template"), WINDOW)).alias("at", "h"))


def item_windows(benchmark: DataFrame) -> DataFrame:
    """item_id, item_at, h, item_template, item_raw (the window's tokens), item_windows (how many the item has).

    A window of placeholders only is no template: every table of numbers would meet every item with a row of numbers."""
    items = tokens(benchmark.filter("item_id is not null").dropDuplicates(["item_id"]), ["item_id"], "text")
    cut = lambda name: F.slice(f"cut.{name}", F.col("item_at") + 1, WINDOW).alias(f"item_{name}")
    items = items.select("item_id", "cut", F.posexplode(common.window_hashes(F.col("cut.template"), WINDOW)).alias("item_at", "h")).select("item_id", "item_at", "h", cut("template"), cut("raw"))
    items = items.filter(F.exists("item_template", lambda t: ~t.isin(NAME, NUMBER, UNIT)))
    return items.withColumn("item_windows", F.count(F.lit(1)).over(W.partitionBy("item_id")))


def occurrences(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id, shift, windows: the occurrences of benchmark items in texts that count.

    Windows of texts are joined by hash alone; only the texts of occurrences with slots are cut again for their values."""
    items = common.materialise(item_windows(benchmark))
    n_items = items.count()
    holders = F.exists("item_template", lambda t: t.isin(NAME, NUMBER, UNIT)).alias("slotted")
    docs = docs.select("doc_id", "text", F.xxhash64("doc_id", "text").alias("row_key"))
    places = items.select("item_id", "item_at", "h", "item_windows", holders)
    hits = windows(docs, ["doc_id", "row_key"], "text").join(common.small_side(places, n_items, MAX_BROADCAST), "h").select(
        "doc_id", "row_key", "item_id", "item_at", "at", (F.col("at") - F.col("item_at")).alias("shift"), "item_windows", "slotted")
    hits = common.materialise(hits)
    found = hits.groupBy("doc_id", "item_id", "shift").agg(F.count_distinct("item_at").alias("windows"), F.max("item_windows").alias("item_windows"))
    found = found.filter(F.col("windows") >= F.least(F.lit(ENOUGH), F.ceil(F.col("item_windows") / 2)))
    found = common.materialise(found)
    asked = hits.filter("slotted").join(found.select("doc_id", "item_id", "shift"), ["doc_id", "item_id", "shift"], "left_semi")
    asked = common.materialise(asked.groupBy("row_key").agg(F.collect_set(F.struct("doc_id", "item_id", "shift", "item_at", "at")).alias("hits")))
    cut = tokens(docs.join(common.small_side(asked, asked.count(), MAX_BROADCAST), "row_key"), ["hits"], "text")
    # The slots of a window: (item's value, text's value) wherever the template has a placeholder.
    values = cut.select(F.explode(F.transform("hits", lambda x: F.struct(x.alias("x"), F.slice("cut.raw", x["at"] + 1, WINDOW).alias("raw")))).alias("v")).select("v.x.*", "v.raw")
    values = values.join(common.small_side(items.select("item_id", "item_at", "item_raw", "item_template"), n_items, MAX_BROADCAST), ["item_id", "item_at"])
    pairs = F.filter(F.arrays_zip(F.col("item_template").alias("t"), F.col("item_raw").alias("i"), F.col("raw").alias("d")), lambda s: s["t"].isin(NAME, NUMBER, UNIT))
    slots = values.select("doc_id", "item_id", "shift", F.explode(pairs).alias("s")).groupBy("doc_id", "item_id", "shift", F.col("s.i").alias("i"))
    # At most as many values as the item has slots. A name may stand whole or in part: Mary Jones, then Mary.
    shortest = F.array_min(F.transform("values", lambda v: F.struct(F.length(v).alias("n"), v.alias("v"))))["v"]
    around = lambda v: F.concat(F.lit(_WITHIN), v, F.lit(_WITHIN))
    parted = slots.agg(F.collect_set(F.struct("s.t", "s.d")).alias("found")).withColumn("values", F.array_distinct(F.transform("found", lambda v: v["d"]))).filter("size(values) > 1")
    alike = F.forall("found", lambda v: v["t"] == NAME) & F.forall("values", lambda v: F.contains(around(v), around(shortest)))
    broken = parted.filter(~alike).select("doc_id", "item_id", "shift").distinct()
    return found.join(broken, ["doc_id", "item_id", "shift"], "left_anti").select("doc_id", "item_id", "shift", "windows")


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_items, item_id (the smallest), windows (of the largest occurrence): texts that hold benchmark items."""
    return occurrences(docs, benchmark).groupBy("doc_id").agg(
        F.count_distinct("item_id").alias("n_items"), F.min("item_id").alias("item_id"), F.max("windows").alias("windows"))


def op10_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.documents(spark, sf_dir)
    hits = common.materialise(contaminated(docs.select("doc_id", "text"), common.table(spark, sf_dir, "benchmark")))
    return docs.select("doc_id").join(hits, "doc_id", "left").select(
        "doc_id", F.col("item_id").isNotNull().alias("contaminated"), F.coalesce("n_items", F.lit(0).cast("long")).alias("n_items"), "item_id",
        F.coalesce("windows", F.lit(0).cast("long")).alias("windows"), F.col("item_id").isNull().alias("kept"))


def _sql(table: str, key: str) -> str:
    """raw and template of every text in SQL without look-around: runs are cut apart and looked at with their neighbours."""
    starters = ", ".join(f"'{w}'" for w in _STARTERS.split("|"))
    return f"""
  SELECT {key}, string_split(trim(regexp_replace(lower(replace(canon, chr(1), '')), '[^\\p{{L}}\\p{{N}}\\x02]+', ' ', 'g')), ' ') AS raw,
   string_split(trim(regexp_replace(regexp_replace(trim(regexp_replace(lower(regexp_replace(canon, '\\x01[^\\x01]+\\x01', '{NAME}', 'g')), '[^\\p{{L}}\\p{{N}}\\x02]+', ' ', 'g')),
     '\\p{{N}}[\\p{{N}}\\x02]*', '{NUMBER}', 'g') || ' ', '{NUMBER} ({UNITS}) ', '{NUMBER} {UNIT} ', 'g')), ' ') AS template
  FROM (SELECT {key}, regexp_replace(array_to_string(list_transform(w, lambda x, i: CASE
     WHEN (regexp_full_match(x, '(\\p{{Lu}}\\p{{Ll}}+)+') AND (x NOT IN ({starters})
        OR (w[i - 1] = ' ' AND regexp_matches(w[i - 2], '\\p{{Ll}}$')) OR regexp_matches(w[i - 1], '[,;] $')))
       OR (regexp_full_match(x, '\\p{{Lu}}') AND w[i + 1] IN (chr(39), chr(8217)) AND regexp_matches(w[i + 2], '^\\p{{Lu}}\\p{{Ll}}')) THEN chr(1) || x || chr(1)
     ELSE x END), ''), '\\x01[ \\x27\\x{{2019}}-]\\x01', chr(2), 'g') AS canon
   FROM (SELECT {key}, regexp_extract_all(array_to_string(list_transform(n, lambda x, i: CASE
       WHEN x NOT IN ('.', ',') OR i = 1 OR i = len(n) THEN x WHEN x = ',' AND length(n[i + 1]) = 3 THEN '' ELSE chr(2) END), ''), '[\\p{{L}}\\p{{N}}]+|[^\\p{{L}}\\p{{N}}]+') AS w
    FROM (SELECT {key}, regexp_extract_all(translate(coalesce(text, ''), chr(1) || chr(2), '  '), '\\p{{N}}+|[^\\p{{N}}]+') AS n FROM {table})))"""


_HOLDERS = f"('{NAME}', '{NUMBER}', '{UNIT}')"
ORACLE = f"""
WITH d AS ({_sql('documents', 'doc_id')}), i AS ({_sql('benchmark', 'item_id')}),
dw AS (SELECT doc_id, p, raw[p:p + {WINDOW - 1}] AS r, template[p:p + {WINDOW - 1}] AS w FROM (SELECT *, unnest(range(1, len(template) - {WINDOW - 2})) AS p FROM d WHERE len(template) >= {WINDOW})),
iw AS (SELECT *, count(*) OVER (PARTITION BY item_id) AS n FROM (
  SELECT item_id, p, raw[p:p + {WINDOW - 1}] AS r, template[p:p + {WINDOW - 1}] AS w FROM (SELECT *, unnest(range(1, len(template) - {WINDOW - 2})) AS p FROM i WHERE len(template) >= {WINDOW}))
  WHERE len(list_filter(w, lambda t: t NOT IN {_HOLDERS})) > 0),
hit AS (SELECT doc_id, item_id, dw.p - iw.p AS shift, iw.p AS ipos, n, iw.r AS ir, dw.r AS dr, iw.w AS w FROM dw JOIN iw ON dw.w = iw.w),
occ AS (SELECT doc_id, item_id, shift, count(DISTINCT ipos) AS windows FROM hit GROUP BY ALL HAVING count(DISTINCT ipos) >= least({ENOUGH}, ceil(max(n) / 2))),
slot AS (SELECT doc_id, item_id, shift, ir[k] AS iv, dr[k] AS dv, w[k] AS t FROM (SELECT *, unnest(range(1, {WINDOW + 1})) AS k FROM hit) WHERE w[k] IN {_HOLDERS}),
value AS (SELECT doc_id, item_id, shift, iv, list(DISTINCT dv) AS vs, bool_and(t = '{NAME}') AS names, arg_min(dv, struct_pack(n := length(dv), v := dv)) AS short FROM slot GROUP BY ALL HAVING count(DISTINCT dv) > 1),
broken AS (SELECT DISTINCT doc_id, item_id, shift FROM value WHERE NOT (names AND len(list_filter(vs, lambda v: NOT contains(chr(2) || v || chr(2), chr(2) || short || chr(2)))) = 0)),
good AS (SELECT * FROM occ ANTI JOIN broken USING (doc_id, item_id, shift)),
per AS (SELECT doc_id, count(DISTINCT item_id) AS n_items, min(item_id) AS item_id, max(windows) AS windows FROM good GROUP BY doc_id)
SELECT doc_id, per.item_id IS NOT NULL AS contaminated, coalesce(n_items, 0)::BIGINT AS n_items, per.item_id, coalesce(windows, 0)::BIGINT AS windows, per.item_id IS NULL AS kept
FROM documents LEFT JOIN per USING (doc_id)
"""
