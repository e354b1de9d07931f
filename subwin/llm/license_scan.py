"""License scans: whole texts looked up by the digest of their canonical form.

The canonical form leaves out what licence texts may vary in: case, copyright statements, kinds of quotation
marks and dashes, punctuation, white space, and spellings that the public matching guidelines for
licence lists hold to be equal. The digest of a document's whole canonical text is hash-joined to the
digests of known licences; a known text given in another case, layout or year is found, one with other
words is not.

Defined results: a null text is an empty one; an empty canonical text matches nothing; a digest that
several licences share gives the least id; rows with a null or repeated doc_id each get a row. Other
columns are ignored. All of it is built-in functions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from subwin.llm.common import table
from subwin.llm.license_texts import KNOWN

#: Spellings that count as equal, as words of the canonical form, the first becoming the second.
SPELLINGS = {
    "acknowledgement": "acknowledgment", "analog": "analogue", "analyze": "analyse", "artifact": "artefact", "authorization": "authorisation",
    "authorized": "authorised", "caliber": "calibre", "canceled": "cancelled", "catalog": "catalogue", "categories": "category",
    "center": "centre", "emphasized": "emphasised", "favor": "favour", "favorite": "favourite", "fulfil": "fulfill",
    "fulfilment": "fulfillment", "initialize": "initialise", "judgement": "judgment", "labeling": "labelling", "labor": "labour",
    "licence": "license", "licenced": "licensed", "licences": "licenses", "maximize": "maximise", "modeled": "modelled", "modeling": "modelling",
    "noncommercial": "non commercial", "offense": "offence", "optimize": "optimise", "organization": "organisation", "organize": "organise",
    "practice": "practise", "program": "programme", "realize": "realise", "recognize": "recognise", "signaling": "signalling",
    "sublicence": "sublicense", "sublicences": "sublicenses", "utilization": "utilisation", "while": "whilst", "wilful": "willful",
}

#: The same of two words.
PHRASES = {"copyright owner": "copyright holder", "copyright owners": "copyright holders", "per cent": "percent", "sub license": "sublicense", "non infringement": "noninfringement"}

#: A statement, in lower case, of whose copyright it is: at the start of a line, with a mark or a year, up to the end of the line or
#: to the first words of a licence on that line, which stay. The copyright notice of a licence's own sentences is none.
STATEMENT = r"^[^a-z0-9\n]*(?:copyright[^a-z\n]*(?:\(c\)|©|[0-9]{4})|\(c\)|©)[^\n]*?($|permission is |permission to |redistribution and |licensed under |this (?:software|program|source|work|is) )"
NOT_WORD = r"[^\p{L}\p{N}]+"


def _doubled(phrase: str) -> str:
    """A phrase where each word stands between two spaces of its own, so that plain replacement sees whole words."""
    return " " + phrase.replace(" ", "  ") + " "


EQUAL = {_doubled(one): _doubled(other) for one, other in (SPELLINGS | PHRASES).items()}


def canonical(text: Column) -> Column:
    """The canonical form: lower-case words with one space between them."""
    text = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), "(?md)" + STATEMENT, " $1")
    text = F.trim(F.regexp_replace(text, NOT_WORD, " "))
    spelt = F.concat(F.lit(" "), F.replace(text, F.lit(" "), F.lit("  ")), F.lit(" "))
    for one, other in EQUAL.items():
        spelt = F.replace(spelt, F.lit(one), F.lit(other))
    return F.when(text.rlike("(^| )(" + "|".join([*SPELLINGS, *PHRASES]) + ")( |$)"), F.trim(F.replace(spelt, F.lit("  "), F.lit(" ")))).otherwise(text)


def known_digests(spark: SparkSession, known=KNOWN) -> DataFrame:
    """canonical_sha256 and license_id of known texts: a list of (id, text) or a frame of license_id, text."""
    rows = known if isinstance(known, DataFrame) else spark.createDataFrame(list(known), "license_id string, text string")
    return rows.select("license_id", canonical(F.col("text")).alias("form")).where("form <> ''").groupBy(F.sha2("form", 256).alias("canonical_sha256")).agg(F.min("license_id").alias("license_id"))


def scan_licenses(docs: DataFrame, known: DataFrame) -> DataFrame:
    """doc_id, canonical_sha256 and license_id (null: none) of each document."""
    forms = docs.select("doc_id", F.sha2(canonical(F.col("text")), 256).alias("canonical_sha256"))
    return forms.join(known, "canonical_sha256", "left").select("doc_id", "canonical_sha256", "license_id")


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"), known_digests(spark))


def _sql_form(text: str) -> str:
    form = f"regexp_replace(lower(coalesce({text}, '')), '(?m){STATEMENT}', ' \\1', 'g')"
    form = f"' ' || replace(trim(regexp_replace({form}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')), ' ', '  ') || ' '"
    for one, other in EQUAL.items():
        form = f"replace({form}, '{one}', '{other}')"
    return f"trim(replace({form}, '  ', ' '))"


def _sql() -> str:
    values = ", ".join("('{}', '{}')".format(*(x.replace("'", "''") for x in row)) for row in KNOWN)
    return f"""
WITH known AS (SELECT sha256({_sql_form("text")}) AS canonical_sha256, min(license_id) AS license_id FROM (VALUES {values}) AS t(license_id, text) GROUP BY 1),
forms AS (SELECT doc_id, sha256({_sql_form("text")}) AS canonical_sha256 FROM documents)
SELECT doc_id, canonical_sha256, license_id FROM forms LEFT JOIN known USING (canonical_sha256)
"""


OP8_SQL = _sql()
