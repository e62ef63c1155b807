"""Licence scans by canonical digest lookup, with DataFrame functions only.

Texts are brought to a canonical form (case, spelling, copyright statements, punctuation, white space), and the digest of the
entire form is looked up among those of known licences in a hash join. Lines are looked up in the same way, so that a
licence statement within a document is found by its whole line.
"""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Spellings that count as equal, and licence texts.
SPELLINGS = [("licence", "license"), ("licenced", "licensed"), ("sublicence", "sublicense"), ("organisation", "organization"), ("authorise", "authorize"), ("merchantibility", "merchantability"), ("fulfil", "fulfill"), ("noninfringement", "non infringement"), ("https", "http"), ("favour", "favor"), ("acknowledgement", "acknowledgment")]
TEXTS = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0."],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3."],
    "MIT": [
        "Released under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\nTHE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    ],
    "ISC": ['Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\n\nTHE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.'],
    "0BSD": ['Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n\nTHE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.'],
}
WARRANTY = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT {who} BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
CLAUSES = [
    "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
]
#: Title lines that stand before a text; a line of reserved rights may follow the copyright line.
TITLES = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)"],
    "ISC": ["ISC License", "The ISC License", "ISC License (ISC)"],
    "0BSD": ["BSD Zero Clause License", "Zero-Clause BSD"],
    "BSD-2-Clause": ["BSD 2-Clause License", "The 2-Clause BSD License", 'BSD 2-Clause "Simplified" License', "Simplified BSD License"],
    "BSD-3-Clause": ["BSD 3-Clause License", "The 3-Clause BSD License", 'BSD 3-Clause "New" or "Revised" License', "New BSD License", "BSD License"],
}
#: The last words of a long text's terms; an appendix on how to apply them may be missing.
ENDS = ("END OF TERMS AND CONDITIONS",)
#: Words after "copyright" at the head of a wrapped line that go on with a sentence rather than name a holder.
GOES_ON = "notices?|licen[cs]es?|licen[cs]ed|laws?|holders?|owners?|owned|ownership|statements?|interests?|disclaimers?|protections?|permissions?|treaty|treaties|status|information|infringements?|term|and|or|on|in|is|are|of|for|as|to|under|with|that|which|applies|does|may|must|shall"


def _full_texts() -> dict[str, list[str]]:
    """TEXTS, the BSD bodies, and the texts of ``license_texts`` with and without their appendix; short bodies by each title, too."""
    out = {name: list(ts) for name, ts in TEXTS.items()}
    for name, n in (("BSD-2-Clause", 2), ("BSD-3-Clause", 3)):
        for who in ("HOLDER OR CONTRIBUTORS", "OWNER OR CONTRIBUTORS", "HOLDERS OR CONTRIBUTORS"):
            for mark in ("{}. ", "* "):
                clauses = "\n".join(mark.format(i + 1) + c for i, c in enumerate(CLAUSES[:n]))
                out.setdefault(name, []).append(f"Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n\n{clauses}\n\n{WARRANTY.format(who=who)}")
    for path in sorted(Path(__file__).with_name("license_texts").glob("*.txt")):
        text = path.read_text(encoding="utf-8")
        out.setdefault(path.stem, []).append(text)
        for end in ENDS:
            if end in text:
                out[path.stem].append(text[: text.index(end) + len(end)])
                out[path.stem].append(text[: text.index(end)])
    for name, titles in TITLES.items():
        bodies = [t for t in out[name] if "\n" in t]
        out[name] += ["\n\n".join((*title, *rights, t)) for t in bodies for title in ([], *([x] for x in titles)) for rights in ([], ["All rights reserved."]) if title or rights]
    return out


TEXTS = _full_texts()


def canonical(text: Column) -> Column:
    """Lower case; copyright statements out; all but letters and digits to single spaces; equal spellings; trimmed.

    A line is a copyright statement if "copyright" at its head is followed by a sign, a year, or a holder, or if a sign is; a
    wrapped sentence that goes on with "copyright notice" and the like stays. Case and punctuation follow ASCII, so that the form is the same in every engine; other characters stay as they are.
    """
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    out = F.translate(F.coalesce(text, F.lit("")), upper, lower)
    out = F.regexp_replace(out, rf"(^|\n)[ \t#*/]*(?:©|\(c\)(?=[^\n]*(?:copyright|(?:19|20)[0-9][0-9]))|copyright(?![a-z.,;)]|[ \t]*(?:\n|$|(?:{GOES_ON})(?![a-z]))))[^\n]*", "\n")
    out = F.concat(F.lit(" "), F.regexp_replace(out, r"[\x00-/:-@\[-`{-\x7f]+", "  "), F.lit(" "))
    for a, b in SPELLINGS:
        out = F.replace(out, F.lit(f" {a} "), F.lit(f" {b} "))
    return F.trim(F.regexp_replace(out, " +", " "))


def known(spark: SparkSession, texts: dict[str, list[str]] | None = None) -> DataFrame:
    """(digest, license) of the known texts; a digest that several licences have goes to the one that sorts first."""
    rows = [(name, t) for name, ts in (TEXTS if texts is None else texts).items() for t in ts]
    df = spark.createDataFrame(rows, "license string, text string")
    return df.select(F.sha2(canonical(F.col("text")), 256).alias("digest"), "license").groupBy("digest").agg(F.min("license").alias("license"))


def scan(docs: DataFrame, digests: DataFrame, id_col: str = "doc_id", text_col: str = "text", limit: int = 1_000) -> DataFrame:
    """One row per row of ``docs``: (id_col, license, n_lines, line_licenses).

    ``license`` is that of the entire text or null; ``n_lines`` counts the lines that are entire licence texts, and
    ``line_licenses`` names them, sorted and joined by commas (empty if none). Null and empty texts match nothing. Digests
    are broadcast while they are fewer than ``limit``, counted first, and joined by a shuffle beyond it. Ids may be null or
    repeated; other columns are not read.
    """
    few = digests.limit(limit).count() < limit
    side = F.broadcast(digests) if few else digests
    src = docs.select(F.col(id_col).alias("strata_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("strata_text"))
    if few:
        # A row's own lines are looked up in an array of digests: nothing is exploded or shuffled.
        pairs = [F.lit(v) for r in digests.collect() for v in (r["digest"], r["license"])]
        table = F.create_map(*pairs) if pairs else F.from_json(F.lit("{}"), "map<string,string>")
        lines = F.filter(F.transform(F.split("strata_text", "\n"), lambda x: F.try_element_at(table, F.sha2(canonical(x), 256))), lambda x: x.isNotNull())
        out = src.withColumn("digest", F.sha2(canonical(F.col("strata_text")), 256)).join(side, "digest", "left").withColumn("found", lines)
        return out.select(F.col("strata_id").alias(id_col), "license", F.size("found").cast("long").alias("n_lines"), F.array_join(F.array_sort(F.array_distinct("found")), ",").alias("line_licenses"))
    keyed = src.withColumn("strata_row", F.monotonically_increasing_id())
    keyed = keyed.withColumn("digest", F.sha2(canonical(F.col("strata_text")), 256)).join(side, "digest", "left").drop("digest")
    found = keyed.select("strata_row", F.explode(F.split("strata_text", "\n")).alias("line")).withColumn("digest", F.sha2(canonical(F.col("line")), 256)).join(digests.withColumnRenamed("license", "hit"), "digest")
    per = found.groupBy("strata_row").agg(F.count("*").alias("n_lines"), F.array_join(F.array_sort(F.collect_set("hit")), ",").alias("line_licenses"))
    return keyed.join(per, "strata_row", "left").select(F.col("strata_id").alias(id_col), "license", F.coalesce("n_lines", F.lit(0)).cast("long").alias("n_lines"), F.coalesce("line_licenses", F.lit("")).alias("line_licenses"))
