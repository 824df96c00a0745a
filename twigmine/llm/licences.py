"""Licence scan: hash-join of canonical texts to known licence digests, without Python on the executors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import store

#: Places of the filter by length that lines pass before they are hashed.
LENGTHS = 4096

# Notices and short licences in public use, by SPDX name.
NOTICES = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Released under the Apache License, Version 2.0."),
    ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0-only", "Licensed under the GNU General Public License, version 3."),
    ("GPL-2.0-only", "This work is licensed under the GNU General Public License, version 2."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."),
    ("0BSD", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."),
    ("MIT", "MIT License\n\nPermission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
]
# Whole licences by SPDX name: characters and SHA-256 of the canonical form of their published text.
WHOLE = [
    ("Apache-2.0", 9927, "6074c3536c43b739207170b87d1681477d0f07374ed3d862ba461334cce848e3"),
    ("Artistic-1.0-Perl", 5833, "e963bc30f4d3c45f45030c34409ee37315564625649c1394e32bb5ddd99e01b2"),
    ("BSD-3-Clause", 1361, "21ce5e311a0ef74591e636cf6d0a236029bcaa0ee86324ac68d5748657aa8651"),
    ("CC0-1.0", 6692, "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f"),
    ("GFDL-1.2", 19584, "5379e6f33e826ba185b23fd11a414555c2161fda481478babd1e73a3ae098a71"),
    ("GFDL-1.3", 22020, "93d6108daecdddc5f284cf8f2512fb0d72f6e9ee12381feb9704ba194b00c3e6"),
    ("GPL-1.0", 11766, "ec8a6b7d70e9f225b63d3962ed5b4721373f5535d7b967a06722b0d621f6892a"),
    ("GPL-2.0", 17118, "331b500eb3c5ee796906547305df82fff4a35b3aa03c1d3ea84d32078292b2e6"),
    ("GPL-3.0", 33409, "a8cd54d6683aa630f0b8d05d56184ad91dc486756da2df61c94d3e4e8d5ecb68"),
    ("LGPL-2.0", 24130, "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908"),
    ("LGPL-2.1", 25217, "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891"),
    ("LGPL-3.0", 7104, "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", 22448, "26ba73e836ecb04fe87d5eca80ca27cff1afa2d7683455be1517bd23b8d27986"),
    ("MPL-2.0", 14341, "f82071285728ca3ec7685ee9bc4acdae0b8267142a4d20b8f1805eabedb4a98a"),
]
# Spellings that count as one, after the public matching guidelines of SPDX.
SPELLINGS = [
    ("acknowledgement", "acknowledgment"), ("analogue", "analog"), ("analyse", "analyze"), ("artefact", "artifact"), ("authorisation", "authorization"), ("authorised", "authorized"), ("calibre", "caliber"), ("cancelled", "canceled"),
    ("catalogue", "catalog"), ("categorise", "categorize"), ("centre", "center"), ("emphasised", "emphasized"), ("favour", "favor"), ("favourite", "favorite"), ("fulfil", "fulfill"), ("fulfilment", "fulfillment"), ("honour", "honor"),
    ("initialise", "initialize"), ("judgement", "judgment"), ("labelling", "labeling"), ("labour", "labor"), ("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("maximise", "maximize"), ("modelled", "modeled"),
    ("modelling", "modeling"), ("merchantibility", "merchantability"), ("noncommercial", "non commercial"), ("offence", "offense"), ("optimise", "optimize"), ("organisation", "organization"), ("organise", "organize"), ("practise", "practice"),
    ("programme", "program"), ("realise", "realize"), ("recognise", "recognize"), ("signalling", "signaling"), ("sub license", "sublicense"), ("utilisation", "utilization"), ("whilst", "while"), ("wilful", "willful"),
    ("per cent", "percent"), ("copyright owner", "copyright holder"), ("copyright owners", "copyright holders"),
]

#: Lines of nothing but a copyright statement; its year or sign must follow the word.
COPYRIGHT_LINE = r"(^|\n)[^\p{L}\p{N}\n]*(copyright|©|\(c\))[ \t]*(\(c\)|©|[0-9]{4}|by )[^\n]*"
ALL_RIGHTS = r"(^|\n)[^\p{L}\p{N}\n]*all rights reserved[^\p{L}\p{N}\n]*"


def canonical_lines(text: Column) -> Column:
    """Text in canonical form, line ends kept: one \\n between lines that have words, words parted by one space."""
    t = F.lower(F.coalesce(text.cast("string"), F.lit("")))
    t = F.regexp_replace(t, COPYRIGHT_LINE, r"$1")
    t = F.regexp_replace(t, ALL_RIGHTS, r"$1")
    t = F.regexp_replace(t, r"[^\p{L}\p{N}\n]+", " ")
    # Every word stands between two blanks of its own, so spellings are whole words.
    t = F.concat(F.lit(" "), F.replace(F.replace(t, F.lit(" "), F.lit("  ")), F.lit("\n"), F.lit(" \n ")), F.lit(" "))
    for other, spelled in SPELLINGS:
        t = F.replace(t, F.lit(f" {other.replace(' ', '  ')} "), F.lit(f" {spelled.replace(' ', '  ')} "))
    return F.btrim(F.regexp_replace(F.regexp_replace(t, r" *\n[ \n]*", "\n"), " +", " "), F.lit(" \n"))


def canonical(text: Column) -> Column:
    """Text in canonical form, all white space one space: what is hashed."""
    return F.translate(canonical_lines(text), "\n", " ")


def known_licences(spark: SparkSession, texts: list[tuple[str, str]] | None = None) -> DataFrame:
    """licence, digest, n of the known texts (n: length of the canonical text); of texts with one canonical form the first name counts.

    Without texts: NOTICES and WHOLE.  Texts without a word in them are no known texts."""
    raw = spark.createDataFrame([(n, t) for n, t in (NOTICES if texts is None else texts)], "licence string, known_text string")
    form = canonical(F.col("known_text"))
    known = raw.select("licence", F.sha2(form, 256).alias("digest"), F.length(form).alias("n"))
    if texts is None:
        known = known.union(spark.createDataFrame([(name, digest, n) for name, n, digest in WHOLE], "licence string, digest string, n int"))
    return known.filter("n > 0").groupBy("digest", "n").agg(F.min("licence").alias("licence"))


def scan(docs: DataFrame, known: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: id, canonical_sha256, licence (of the whole text, else null), notices (names found in single lines, sorted).

    The whole canonical text is hashed and joined to the known digests.  Its lines are looked up in the same
    digests, hashed only if a known text has their length modulo LENGTHS.  Null and empty texts have the digest of the empty
    text and no licence; ties and repeated rows each get the same answer; an empty table gives an empty one.

    Texts are read once; digests go to the shared folder, and only they are joined, by Spark's own choice of join: the known table may be of any size.
    """
    spark = docs.sparkSession
    known = store((known_licences(spark) if known is None else known.filter("n > 0")).select("digest", "licence", "n"), "licence-known")
    # As many places as LENGTHS, whatever the size of the known table.
    lengths = {r[0] for r in known.select(F.col("n") % LENGTHS).distinct().collect()}
    places = F.lit("".join("1" if k in lengths else "0" for k in range(LENGTHS)))
    likely = lambda x: F.substring(places, F.length(x) % LENGTHS + 1, F.lit(1)) == "1"
    forms = docs.select(F.col(id_col).alias("id"), canonical_lines(F.col(text_col)).alias("form"))
    lines = F.array_distinct(F.transform(F.filter(F.split("form", "\n"), lambda x: (x != "") & likely(x)), lambda x: F.sha2(x, 256)))
    hashed = store(forms.select("id", F.sha2(F.translate("form", "\n", " "), 256).alias("canonical_sha256"), lines.alias("lines")).withColumn("row", F.monotonically_increasing_id()), "licence-hashes")
    names = known.select(F.col("digest").alias("line"), "licence")
    found = hashed.select("row", F.explode("lines").alias("line")).join(names, "line").groupBy("row").agg(F.array_sort(F.collect_set("licence")).alias("notices"))
    marked = hashed.drop("lines").join(found, "row", "left").join(known.select(F.col("digest").alias("canonical_sha256"), "licence"), "canonical_sha256", "left")
    return marked.select(F.col("id").alias(id_col), "canonical_sha256", "licence", F.coalesce("notices", F.expr("array()").cast("array<string>")).alias("notices"))
