"""License scan: ordered signature rules behind keyword gates, with containment suppression. DataFrame functions only.

A text is lower-cased (A-Z) and rewritten to its words, each between two blanks (`` w1  w2  w3 ``), in one pass. Counts
and positions of words then are counts of blanks, and a phrase is a literal that neighbours cannot take a blank from.
Rules are a literal table (keyword, regular expression over the rewritten text, label, order, confidence). A rule's
expression runs only on texts that hold its keyword; texts that hold no general cue at all skip the table.
Detections of one document are merged inside its own row: sorted by start, longest first, then rule order; one that
lies inside an earlier one is suppressed, which also resolves equal spans by priority. No shuffle, no Python.

Defined cases: null or empty text has no words and no labels, score 0; texts of any length are scanned whole; repeated
rows give repeated results; further columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from revnn.llm.common import ascii_lower, bind, prefix_sums, table

NOT_WORD = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: Fixed values of the contract: phrase, label.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Every rule's text holds one of these words, or begins with one.
CUES = ("licen", "spdx", "copyright", "cc", "creative", "public", "gpl", "lgpl", "agpl", "unlicense", "wtfpl", "copyleft", "proprietary", "rights", "mpl", "apache", "bsd", "open", "mit  0", "mit  no")

#: Families of names, most specific first: label, what the name looks like in words (regular expression over ``w`` tokens
#: joined by one blank), and the literal keyword that must be there.
FAMILIES = (
    ("agpl-3", r"(?:gnu )?affero general public (?:license|licence)(?: v(?:ersion)?)? ?3(?: 0)?", "affero"),
    ("agpl-1", r"affero general public (?:license|licence) (?:v(?:ersion)? ?)?1(?: 0)?", "affero"),
    ("agpl", r"(?:gnu )?affero (?:general public )?(?:license|licence|gpl)", "affero"),
    ("agpl-3", r"agpl ?v?3(?: 0)?", "agpl"),
    ("lgpl-3", r"(?:gnu )?lesser general public (?:license|licence)(?: v(?:ersion)?)? ?3(?: 0)?", "lesser"),
    ("lgpl-2.1", r"(?:gnu )?lesser general public (?:license|licence)(?: v(?:ersion)?)? ?2 1", "lesser"),
    ("lgpl-2", r"(?:gnu )?library general public (?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "library"),
    ("lgpl", r"(?:gnu )?(?:lesser|library) general public (?:license|licence)", "general"),
    ("lgpl-3", r"lgpl ?v?3(?: 0)?", "lgpl"),
    ("lgpl-2.1", r"lgpl ?v?2 1", "lgpl"),
    ("lgpl", r"lgpl", "lgpl"),
    ("gpl-3", r"(?:gnu )?general public (?:license|licence)(?: v(?:ersion)?)? ?3(?: 0)?", "general"),
    ("gpl-2", r"(?:gnu )?general public (?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "general"),
    ("gpl-1", r"(?:gnu )?general public (?:license|licence)(?: v(?:ersion)?)? ?1(?: 0)?", "general"),
    ("gpl", r"gnu (?:general public (?:license|licence)|gpl)", "gnu"),
    ("gpl-3", r"gpl ?v?3(?: 0)?", "gpl"),
    ("gpl-2", r"gpl ?v?2(?: 0)?", "gpl"),
    ("gfdl-1.3", r"gnu free documentation (?:license|licence)(?: version)? 1 3", "documentation"),
    ("gfdl", r"gnu free documentation (?:license|licence)", "documentation"),
    ("apache-2", r"apache (?:software )?(?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "apache"),
    ("apache-1.1", r"apache (?:software )?(?:license|licence)(?: v(?:ersion)?)? ?1 1", "apache"),
    ("apache-1", r"apache (?:software )?(?:license|licence)(?: v(?:ersion)?)? ?1(?: 0)?", "apache"),
    ("apache", r"apache (?:software )?(?:license|licence)", "apache"),
    ("apache-2", r"apache 2 0", "apache"),
    ("mit-0", r"mit (?:no attribution|0)(?: license| licence)?", "mit"),
    ("mit", r"mit (?:x11 )?(?:license|licence)", "mit"),
    ("mit", r"expat (?:license|licence)", "expat"),
    ("x11", r"x11 (?:license|licence)", "x11"),
    ("isc", r"isc (?:license|licence)", "isc"),
    ("bsd-0", r"(?:zero clause|0 clause) bsd(?: license| licence)?", "bsd"),
    ("bsd-2", r"(?:2|two) clause bsd(?: license| licence)?", "bsd"),
    ("bsd-2", r"bsd 2 clause(?: license| licence)?", "bsd"),
    ("bsd-2", r"(?:simplified|freebsd) (?:bsd )?(?:license|licence)", "licen"),
    ("bsd-3", r"(?:3|three) clause bsd(?: license| licence)?", "bsd"),
    ("bsd-3", r"bsd 3 clause(?: license| licence)?", "bsd"),
    ("bsd-3", r"(?:new|modified|revised) bsd (?:license|licence)", "bsd"),
    ("bsd-4", r"(?:4|four) clause bsd(?: license| licence)?", "bsd"),
    ("bsd-4", r"bsd 4 clause(?: license| licence)?", "bsd"),
    ("bsd", r"bsd (?:style )?(?:license|licence)", "bsd"),
    ("mpl-2", r"mozilla public (?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "mozilla"),
    ("mpl-1.1", r"mozilla public (?:license|licence)(?: v(?:ersion)?)? ?1 1", "mozilla"),
    ("mpl", r"mozilla public (?:license|licence)", "mozilla"),
    ("mpl-2", r"mpl ?v?2(?: 0)?", "mpl"),
    ("epl-2", r"eclipse public (?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "eclipse"),
    ("epl-1", r"eclipse public (?:license|licence)(?: v(?:ersion)?)? ?1(?: 0)?", "eclipse"),
    ("epl", r"eclipse public (?:license|licence)", "eclipse"),
    ("cddl-1", r"common development and distribution (?:license|licence)(?: version)?(?: 1 [01])?", "distribution"),
    ("cpl-1", r"common public (?:license|licence)(?: version)?(?: 1 0)?", "common"),
    ("eupl-1.2", r"european union public (?:license|licence)(?: v(?:ersion)?)? ?1 2", "european"),
    ("eupl", r"european union public (?:license|licence)", "european"),
    ("artistic-2", r"artistic (?:license|licence)(?: v(?:ersion)?)? ?2(?: 0)?", "artistic"),
    ("artistic-1", r"artistic (?:license|licence)", "artistic"),
    ("bsl-1", r"boost software (?:license|licence)(?: version)?(?: 1 0)?", "boost"),
    ("zlib", r"zlib(?: libpng)? (?:license|licence)", "zlib"),
    ("psf-2", r"python software foundation (?:license|licence)(?: version)?(?: 2)?", "python"),
    ("postgresql", r"postgresql (?:license|licence)", "postgresql"),
    ("openssl", r"openssl (?:license|licence)", "openssl"),
    ("ofl-1.1", r"(?:sil )?open font (?:license|licence)(?: version)?(?: 1 1)?", "font"),
    ("odbl-1", r"open (?:data commons open )?database (?:license|licence)(?: v?1 0)?", "database"),
    ("odc-by-1", r"open data commons attribution (?:license|licence)", "commons"),
    ("pddl-1", r"(?:open data commons )?public domain dedication and (?:license|licence)", "dedication"),
    ("cc0-1", r"cc0(?: 1 0)?(?: universal)?", "cc0"),
    ("cc0-1", r"creative commons (?:zero|cc0|public domain)", "creative"),
    ("unlicense", r"(?:the )?unlicense", "unlicense"),
    ("wtfpl-2", r"wtfpl(?: v?2)?", "wtfpl"),
    ("ms-pl", r"microsoft public (?:license|licence)", "microsoft"),
    ("ms-rl", r"microsoft reciprocal (?:license|licence)", "microsoft"),
    ("bsl-1.1", r"business source (?:license|licence)(?: 1 1)?", "business"),
    ("sspl-1", r"server side public (?:license|licence)", "server"),
    ("elastic-2", r"elastic (?:license|licence)(?: v?2(?: 0)?)?", "elastic"),
    ("rail", r"(?:creativeml )?open ?rail(?: m)?", "rail"),
    ("vim", r"vim (?:license|licence)", "vim"),
    ("ruby", r"ruby (?:license|licence)", "ruby"),
    ("php-3", r"php (?:license|licence)(?: version)?(?: 3 0?1?)?", "php"),
    ("ncsa", r"(?:university of illinois )?ncsa (?:open source )?(?:license|licence)", "ncsa"),
    ("public-domain", r"(?:released|placed|dedicated) (?:in|into|to) the public domain", "public"),
    ("proprietary", r"all rights reserved", "reserved"),
    ("proprietary", r"proprietary and confidential", "proprietary"),
)
#: Attributes of Creative Commons licences, longest first: they span a family by rule.
CC_PARTS = ("by nc nd", "by nc sa", "by nc", "by nd", "by sa", "by")
CC_WORDS = {"by": "attribution", "nc": "non ?commercial", "nd": "no ?deriv(?:ative)?s?(?: works)?", "sa": "share ?alike"}
CC_VERSIONS = ("4 0", "3 0", "2 5", "2 0", "1 0")
#: Ways to name a licence, surest first: text before the name, confidence.
FRAMES = (
    (r"spdx license identifier ", 1.0),
    (r"(?:licensed|released|distributed|available|provided|published) under (?:the )?(?:terms of (?:the )?)?", 0.95),
    (r"(?:license|licence) ", 0.8),
    (r"", 0.7),
)


def rules() -> list[tuple[str, str, str, int, float]]:
    """keyword, expression, label, order, confidence: families times frames, in order of priority."""
    families = list(FAMILIES)
    for part in CC_PARTS:
        label, words = "cc-" + part.replace(" ", "-"), " ".join(CC_WORDS[x] for x in part.split())
        families += [(f"{label}-{v.replace(' ', '.')}", f"cc {part} {v}", f"  {v.replace(' ', '  ')} ") for v in CC_VERSIONS]
        families += [(label, f"cc {part}", " cc "), (label, f"creative commons {words}(?: international| unported| generic)?", "creative")]
    found = []
    for before, sure in FRAMES:
        for label, name, keyword in families:
            found.append((keyword, rewritten(before + name), label, len(found), sure))
    return found


def rewritten(words: str) -> str:
    """An expression over single-blank words as one over the rewritten text, beginning and ending at word bounds."""
    return " " + words.replace(" ?", "(?:  )?").replace(" ", "  ").replace("(?:    )?", "(?:  )?") + " "


def as_words(text: Column) -> Column:
    """The words of the text, lower-cased, each between two blanks; empty if there are none."""
    inner = F.trim(F.regexp_replace(ascii_lower(F.coalesce(text, F.lit(""))), NOT_WORD, "  "))
    return F.when(inner == "", F.lit("")).otherwise(F.concat(F.lit(" "), inner, F.lit(" ")))


def blanks(s: Column) -> Column:
    return F.length(s) - F.length(F.replace(s, F.lit(" "), F.lit("")))


def count_words(s: Column) -> Column:
    """Words of a rewritten text, or of a piece of one that begins and ends at a word's own blanks."""
    return (blanks(s) / 2).cast("long")


def phrase_places(s: Column, n_words: Column, phrase: str) -> tuple[Column, Column, Column]:
    """Count, smallest and largest start (in words) of a literal phrase."""
    literal = F.lit(" " + phrase.replace(" ", "  ") + " ")
    there = F.contains(s, literal)
    count = F.when(there, (F.length(s) - F.length(F.replace(s, literal, F.lit("")))) / F.length(literal)).otherwise(F.lit(0)).cast("long")
    first = F.when(there, count_words(F.substring_index(s, " " + phrase.replace(" ", "  ") + " ", 1)))
    after = count_words(F.substring_index(s, " " + phrase.replace(" ", "  ") + " ", -1))
    return count, first, F.when(there, n_words - after - len(phrase.split()))


def detections(s: Column, table_of_rules: list | None = None) -> Column:
    """array<struct<start, end, order, label, score>> in words, sorted so that a container precedes what it contains."""
    literal = F.array(*(F.struct(F.lit(k).alias("keyword"), F.lit(e).alias("pattern"), F.lit(x).alias("label"), F.lit(i).alias("order"), F.lit(float(c)).alias("score")) for k, e, x, i, c in (table_of_rules or rules())))
    open_rules = F.filter(literal, lambda r: F.contains(s, r["keyword"]))

    def placed(r: Column, q: Column) -> Column:
        """Words before a hit: those of the gaps up to it and of the hits before it."""
        ends = lambda p: F.transform(q["hits"], lambda h, i: bind(p[i] + q["gaps"][i], lambda at: F.struct(at.alias("start"), (-at - h).alias("minus_end"), r["order"].alias("order"), r["label"].alias("label"), r["score"].alias("score"))))
        return bind(prefix_sums(F.zip_with(q["hits"], F.slice(q["gaps"], F.lit(1), F.size(q["hits"])), lambda h, g: h + g)), ends)

    def spans(r: Column) -> Column:
        hits, gaps = F.regexp_extract_all(s, r["pattern"], F.lit(0)), F.split(s, r["pattern"], -1)
        counted = F.struct(F.transform(hits, count_words).alias("hits"), F.transform(gaps, count_words).alias("gaps"))
        return bind(counted, lambda q: placed(r, q))

    return F.array_sort(F.flatten(F.transform(open_rules, spans)))


def kept_labels(found: Column) -> Column:
    """array<struct<label, score>> after suppression; `found` as of :func:`detections`."""
    start = F.struct(F.lit(-1).cast("long").alias("reach"), F.array().cast("array<struct<label:string,score:double>>").alias("out"))

    def step(acc: Column, d: Column) -> Column:
        end = -d["minus_end"]
        inside = acc["reach"] >= end
        return F.struct(F.greatest(acc["reach"], end).alias("reach"), F.when(inside, acc["out"]).otherwise(F.array_union(acc["out"], F.array(F.struct(d["label"].alias("label"), d["score"].alias("score"))))).alias("out"))

    return F.aggregate(found, start, step, lambda acc: acc["out"])


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score for every row."""
    d = docs.select("doc_id", as_words(F.col("text")).alias("s"))
    d = d.withColumn("n_words", count_words(F.col("s")))
    places = {label: phrase_places(F.col("s"), F.col("n_words"), phrase) for phrase, label in BASE.items()}
    base = F.array_compact(F.array(*(F.when(p[0] > 0, F.lit(label)) for label, p in sorted(places.items()))))
    gate = F.lit(False)
    for cue in CUES:
        gate = gate | F.contains("s", F.lit(f" {cue}"))
    none = F.array().cast("array<struct<label:string,score:double>>")
    more = F.when(gate, kept_labels(detections(F.col("s")))).otherwise(none)
    smallest, largest = F.least(*(p[1] for p in places.values())), F.greatest(*(p[2] for p in places.values()))
    d = d.select("doc_id", "n_words", sum((p[0] for p in places.values()), F.lit(0)).cast("long").alias("n_base"), smallest.alias("first_word"), largest.alias("last_word"), base.alias("base"), more.alias("more"))
    score = F.when(F.size("base") > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max(F.transform("more", lambda m: m["score"])), F.lit(0.0)))
    labels = F.array_sort(F.array_distinct(F.concat("base", F.transform("more", lambda m: m["label"]))))
    return d.select("doc_id", "n_words", "n_base", "first_word", "last_word", F.array_join("base", ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"), score.alias("score"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


QUERIES = {"op10_license_scan": op10_license_scan}
