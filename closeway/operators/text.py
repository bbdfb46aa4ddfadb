"""From texts to closeness statements: sentences, tokens, tags, places, pairs and the two tests.

Everything stays narrow, one nested row per sentence, until statements exist; the only join is to the gazetteer.

Defined results: texts are told apart by doc_id, so the mentions of a row given twice count once; null and empty texts have
no sentences; null names and empty gazetteers match nothing; empty tables give no rows (the funnel one row of zeros).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import BROADCAST_ROWS, Stored, small

# Word classes of the rule tagger.
PREPOSITIONS = ("in", "on", "at", "by", "with", "of", "for", "from", "near", "next", "close", "nearby", "beside", "behind", "within", "inside", "opposite", "to", "far", "away", "north", "south", "east", "west")
DETERMINERS = ("the", "a", "an", "this", "that", "these", "those")
AUXILIARIES = ("is", "was", "are", "were", "be", "been", "has", "have", "had")
PRONOUNS = ("i", "you", "he", "she", "it", "we", "they")
CONJUNCTIONS = ("and", "or", "but", "than", "as")
WORD = "[A-Za-z]+"
TOKEN = "[A-Za-z]+|[0-9]+"


@dataclass(frozen=True)
class Phrase:
    rel_id: int
    phrase: str
    kind: str = "close"


# The relation words on the given tables, and those of real travel texts.
TABLE_LEXICON = (Phrase(0, "in"), Phrase(1, "on"), Phrase(2, "at"), Phrase(3, "by"), Phrase(4, "with"))
TRAVEL_LEXICON = (
    Phrase(0, "next to"), Phrase(1, "close to"), Phrase(2, "near"), Phrase(3, "at"), Phrase(4, "in"), Phrase(5, "nearby"), Phrase(6, "beside"),
    Phrase(7, "north of", "direction"), Phrase(8, "south of", "direction"), Phrase(9, "far from", "remote"), Phrase(10, "away from", "remote"),
)
#: Tag strings allowed between two places: verb in the third person, adverb or participle, prepositions, determiner.
PATTERNS = ("^Z?[RE]?I{1,2}D?$", "^Z?D?N?I{1,2}D?N?$")


def default_lexicon(travel: bool = False) -> tuple[Phrase, ...]:
    return TRAVEL_LEXICON if travel else TABLE_LEXICON


def default_patterns() -> tuple[str, ...]:
    return PATTERNS


def pages_to_text(pages: DataFrame, html: str = "html") -> DataFrame:
    """(page_id, text): comments, scripts, styles and tags removed, the common entities replaced, blanks joined."""
    t = F.regexp_replace(F.col(html), "(?s)<!--.*?-->", " ")
    for tag in ("script", "style"):
        t = F.regexp_replace(t, f"(?is)<{tag}[^>]*>.*?</{tag}>", " ")
    t = F.regexp_replace(t, "(?s)<[^>]*>", " ")
    for entity, ch in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        t = F.replace(t, F.lit(entity), F.lit(ch))
    return pages.select("page_id", F.trim(F.regexp_replace(t, "[ \t\r\n\x0b\f]+", " ")).alias("text"))


def split_sentences(docs: DataFrame) -> DataFrame:
    """(doc_id, sent_id, sentence): parts between . ! ? and line breaks that hold more than blanks."""
    s = docs.select("doc_id", F.posexplode(F.split("text", "[.!?\n]")).alias("sent_id", "sentence"))
    return s.where(F.col("sentence").rlike("[^ ]"))


def tokenize(sentence: Column) -> Column:
    """Runs of ASCII letters or of digits, in order."""
    return F.regexp_extract_all(sentence, F.lit(TOKEN), 0)


def tag_of(token: Column) -> Column:
    """One letter: I preposition, D determiner, Z verb in the third person, P pronoun, K conjunction, C number, E participle, G gerund, R adverb, N else."""
    w = F.lower(token)
    return (
        F.when(w.isin(*PREPOSITIONS), "I").when(w.isin(*DETERMINERS), "D").when(w.isin(*AUXILIARIES), "Z").when(w.isin(*PRONOUNS), "P").when(w.isin(*CONJUNCTIONS), "K")
        .when(w.rlike("^[0-9]+$"), "C").when(w.rlike("^[a-z]+ed$"), "E").when(w.rlike("^[a-z]+ing$"), "G").when(w.rlike("^[a-z]+ly$"), "R").when(w.rlike("^[a-z]*[a-rt-z]s$"), "Z").otherwise("N")
    )


def tokens(sentences: DataFrame) -> DataFrame:
    """(doc_id, sent_id, toks): the sentence's tokens, kept nested."""
    return sentences.select("doc_id", "sent_id", tokenize(F.col("sentence")).alias("toks"))


def tagged(toks: DataFrame) -> DataFrame:
    """Adds ``tags``: one letter per token, as one text."""
    return toks.withColumn("tags", F.array_join(F.transform("toks", tag_of), ""))


#: Bits of the sieve for each name, and most names that it is made for (its size is two bytes a name).
SIEVE_BITS, SIEVE_NAMES = 16, 100_000_000
#: Bits in one bitmap of Spark's bitmap functions.
BITMAP = 32_768


def sifted(cand: DataFrame, names: DataFrame, rows: int) -> DataFrame:
    """The candidates whose name may be among ``rows`` names: a bit per hash, in bitmaps joined by their number.

    All names pass, and of other candidates about one in ``SIEVE_BITS``; so few rows go on to the join by name.
    """
    h = F.pmod(F.xxhash64("name"), F.lit(BITMAP * -(-SIEVE_BITS * rows // BITMAP)))
    part, bit = F.floor(h / BITMAP).cast("int"), (h % BITMAP).cast("int")
    maps = names.select(part.alias("_part"), bit.cast("long").alias("_bit")).groupBy("_part").agg(F.bitmap_construct_agg("_bit").alias("_map"))
    met = cand.withColumns({"_part": part, "_bit": bit}).join(F.broadcast(maps), "_part")  # two bytes a name
    byte = F.conv(F.hex(F.substring("_map", F.expr("_bit div 8 + 1"), F.lit(1))), 16, 10).cast("int")
    return met.where(F.expr("_bit").isNotNull() & ((F.floor(byte / F.pow(F.lit(2), F.col("_bit") % 8)) % 2) == 1)).select(cand.columns)


def entities(toks: DataFrame, gazetteer: DataFrame, max_words: int = 4, most: int = BROADCAST_ROWS) -> DataFrame:
    """(doc_id, sent_id, first, last, name, poi_id, etype): the longest names at each place, leftmost first.

    ``gazetteer`` rows with a null poi_id are places that can't be located. Names are compared in lower case; a name of
    up to ``max_words`` words is looked for at every place. Of overlapping names the earlier, then the longer one stays.
    Up to ``most`` names are broadcast; with more, a sieve of bits takes out nearly all other words before the join.
    """
    first = F.sequence(F.lit(0), F.size("toks") - 1)
    spans = F.flatten(F.transform(first, lambda i: F.transform(F.sequence(F.lit(1), F.least(F.lit(max_words), F.size("toks") - i)), lambda n: F.struct(i.alias("first"), (i + n - 1).alias("last"), F.lower(F.array_join(F.slice("toks", i + 1, n), " ")).alias("name")))))
    cand = toks.where(F.size("toks") >= 1).select("doc_id", "sent_id", F.inline(spans))
    names = gazetteer.groupBy(F.lower("name").alias("name")).agg(F.min("poi_id").alias("poi_id"), F.min("etype").alias("etype"))
    if names.limit(most + 1).count() <= most:
        hits = cand.join(F.broadcast(names), "name")
    else:
        rows = names.count()
        hits = (sifted(cand, names, rows) if rows <= SIEVE_NAMES else cand).join(names, "name")
    # A place's hits are few; they are swept in one row per sentence.
    hit = F.struct("first", (-F.col("last")).alias("neg"), "name", "poi_id", "etype")
    per = hits.groupBy("doc_id", "sent_id").agg(F.array_sort(F.collect_list(hit)).alias("h"))
    start = F.struct(F.lit(-1).alias("end"), F.expr("cast(array() as array<struct<first:int,last:int,name:string,poi_id:bigint,etype:string>>)").alias("kept"))
    sweep = F.aggregate(
        "h",
        start,
        lambda a, x: F.when(x["first"] <= a["end"], a).otherwise(
            F.struct((-x["neg"]).alias("end"), F.concat(a["kept"], F.array(F.struct(x["first"].alias("first"), (-x["neg"]).alias("last"), x["name"].alias("name"), x["poi_id"].cast("long").alias("poi_id"), x["etype"].alias("etype")))).alias("kept"))
        ),
        lambda a: a["kept"],
    )
    return per.select("doc_id", "sent_id", F.inline(sweep))


def entities_by_case(sentences: DataFrame) -> DataFrame:
    """(doc_id, sent_id, name): runs of capitalised words; the variant without a gazetteer."""
    found = F.regexp_extract_all("sentence", F.lit("[A-Z][a-z]+(?: [A-Z][a-z]+)*"), 0)
    return sentences.select("doc_id", "sent_id", F.explode(found).alias("name"))


def geoparse(docs: DataFrame, gazetteer: DataFrame, max_words: int = 1) -> DataFrame:
    """Mentions of places in texts: sentences, tokens and entities in one."""
    return entities(tokens(split_sentences(docs)), gazetteer, max_words)


def geocode(mentions: DataFrame, places: DataFrame, how: str = "left") -> DataFrame:
    """Mentions with x and y; those without a known place keep nulls (``left``) or go (``inner``)."""
    return mentions.join(small(places.select("poi_id", "city_id", "x", "y")), "poi_id", how)


def entity_pairs(toks: DataFrame, mentions: DataFrame, mode: str = "all", max_gap: int = 6) -> DataFrame:
    """(doc_id, sent_id, pi, pj, gap, tags): located pairs, left to right, with the words between them and their tags.

    ``all``: every two places with 1 to ``max_gap`` tokens between; ``adjacent``: neighbours only. Sentences with fewer
    than two places are dropped before pairs are made; a place meets at most the ``max_gap`` + 1 next ones, so a
    sentence's pairs grow with its length and not with its square.
    """
    nested = mentions.where("poi_id is not null").groupBy("doc_id", "sent_id").agg(F.array_sort(F.collect_list(F.struct("first", "last", "poi_id"))).alias("ents"))
    s = nested.where(F.size("ents") >= 2).join(toks, ["doc_id", "sent_id"])
    reach = 1 if mode == "adjacent" else max_gap + 1
    i = F.sequence(F.lit(1), F.size("ents") - 1)
    pair = F.flatten(F.transform(i, lambda k: F.transform(F.slice("ents", k + 1, reach), lambda b: F.struct(F.element_at("ents", k).alias("a"), b.alias("b")))))
    s = s.select("doc_id", "sent_id", "toks", F.explode(pair).alias("p"))
    between = F.col("p.b.first") - F.col("p.a.last") - 1
    s = s.where((between >= 1) & (between <= max_gap))
    gap = F.slice("toks", F.col("p.a.last") + 2, between)
    return s.select("doc_id", "sent_id", F.col("p.a.first").alias("at_i"), F.col("p.b.first").alias("at_j"), F.col("p.a.poi_id").alias("pi"), F.col("p.b.poi_id").alias("pj"), F.lower(F.array_join(gap, " ")).alias("gap"), F.array_join(F.transform(gap, tag_of), "").alias("tags"))


def match_syntax(pairs: DataFrame, patterns: tuple[str, ...] = PATTERNS) -> DataFrame:
    """Pairs whose tags between the places fit one of the patterns."""
    return pairs.where(F.col("tags").rlike("|".join(f"(?:{p})" for p in patterns)))


def match_relation(pairs: DataFrame, lexicon: tuple[Phrase, ...] = TABLE_LEXICON) -> DataFrame:
    """Adds rel_id of the leftmost phrase of the gap, the longest at that place; pairs without one are dropped."""
    phrases = sorted(lexicon, key=lambda p: (-len(p.phrase), p.phrase))
    found = F.regexp_extract("gap", r"(?:^| )(" + "|".join(p.phrase for p in phrases) + r")(?: |$)", 1)
    ids = F.create_map(*[F.lit(x) for p in phrases for x in (p.phrase, p.rel_id)])
    return pairs.withColumn("phrase", found).where("phrase <> ''").withColumn("rel_id", F.element_at(ids, F.col("phrase"))).drop("phrase")


def extract_triplets(docs: DataFrame, gazetteer: DataFrame, patterns: tuple[str, ...] = PATTERNS, lexicon: tuple[Phrase, ...] = TABLE_LEXICON, use_syntax: bool = True, mode: str = "all", max_gap: int = 6, max_words: int = 1, mentions: DataFrame | None = None) -> DataFrame:
    """(doc_id, sent_id, pi, rel_id, pj) with different ends. ``use_syntax=False`` is the baseline by words alone.

    ``mentions`` are the texts' entities where they were found before. Null texts have no sentences.
    """
    toks = tokens(split_sentences(docs))
    pairs = entity_pairs(toks, entities(toks, gazetteer, max_words) if mentions is None else mentions, mode, max_gap).where("pi <> pj")
    return match_relation(match_syntax(pairs, patterns) if use_syntax else pairs, lexicon).select("doc_id", "sent_id", "at_i", "at_j", "pi", "rel_id", "pj")


def keep_closeness(triplets: DataFrame, lexicon: tuple[Phrase, ...]) -> DataFrame:
    """Only statements by words that denote closeness; the lexicon is a literal."""
    return triplets.where(F.col("rel_id").isin([p.rel_id for p in lexicon if p.kind == "close"]))


def relation_edges(triplets: DataFrame) -> DataFrame:
    """(pi, pj, rel_id, cnt): statements per ordered pair and word."""
    return triplets.groupBy("pi", "pj", "rel_id").agg(F.count("*").alias("cnt"))


def relation_graph(edges: DataFrame) -> DataFrame:
    """(pi, pj, rels, n): the words of each ordered pair as an array of (rel_id, cnt)."""
    return edges.groupBy("pi", "pj").agg(F.array_sort(F.collect_list(F.struct("rel_id", "cnt"))).alias("rels"), F.sum("cnt").alias("n"))


def in_city(edges: DataFrame, places: DataFrame) -> DataFrame:
    """Adds city_id and drops pairs whose places lie in different cities."""
    a = places.select(F.col("poi_id").alias("pi"), "city_id")
    b = places.select(F.col("poi_id").alias("pj"), F.col("city_id").alias("_cj"))
    return edges.join(small(a), "pi").join(small(b), "pj").where("city_id = _cj").drop("_cj")


def extraction_funnel(docs: DataFrame, gazetteer: DataFrame, heldout: DataFrame, lexicon: tuple[Phrase, ...] = TABLE_LEXICON, approximate: bool = False) -> DataFrame:
    """One row: texts, mentions, geocoded mentions, statements, pairs, geocode rate, statements per text."""
    known = gazetteer.select("name", "poi_id", "etype").unionByName(heldout.select("name", F.lit(None).cast("long").alias("poi_id"), F.lit(None).cast("string").alias("etype")))
    mentions = Stored(geoparse(docs, known), "mentions").df
    t = extract_triplets(docs, known, lexicon=lexicon, mentions=mentions)
    distinct = (lambda c: F.approx_count_distinct(c)) if approximate else F.count_distinct
    return (
        docs.agg(F.count("*").alias("texts"))
        .join(mentions.agg(F.count("*").alias("mentions"), F.count("poi_id").alias("geocoded")))
        .join(t.agg(F.count("*").alias("triplets"), distinct(F.struct("pi", "pj")).alias("pairs")))
        .withColumn("geocode_rate", F.round(F.col("geocoded") / F.col("mentions"), 6))
        .withColumn("triplets_per_text", F.round(F.col("triplets") / F.col("texts"), 6))
    )


def extraction_quality(found: DataFrame, planted: DataFrame) -> DataFrame:
    """Precision and recall of (pi, rel_id, pj) against planted statements."""
    keys = ["pi", "rel_id", "pj"]
    f, p = found.select(keys).distinct(), planted.select(keys).distinct()
    hit = f.join(p, keys, "left_semi").agg(F.count("*").alias("hits"))
    return hit.join(f.agg(F.count("*").alias("found"))).join(p.agg(F.count("*").alias("planted"))).select("hits", "found", "planted", F.try_divide("hits", "found").alias("precision"), F.try_divide("hits", "planted").alias("recall"))
