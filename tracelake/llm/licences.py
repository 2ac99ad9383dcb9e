"""Licence scan by canonical digest: normalised whole texts, hash-joined to known licence digests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Equivalent spellings, the first replaced by the second.
SPELLINGS = (
    ("sub-licence", "sublicense"),
    ("sub-license", "sublicense"),
    ("licence", "license"),
    ("acknowledgement", "acknowledgment"),
    ("analogue", "analog"),
    ("analyse", "analyze"),
    ("artefact", "artifact"),
    ("authorisation", "authorization"),
    ("authorised", "authorized"),
    ("behaviour", "behavior"),
    ("catalogue", "catalog"),
    ("favour", "favor"),
    ("honour", "honor"),
    ("initialise", "initialize"),
    ("judgement", "judgment"),
    ("labour", "labor"),
    ("non-commercial", "noncommercial"),
    ("organisation", "organization"),
    ("per cent", "percent"),
    ("programme", "program"),
    ("recognise", "recognize"),
    ("utilisation", "utilization"),
    ("whilst", "while"),
    ("wilful", "willful"),
    ("copyright owner", "copyright holder"),
    ("https://", "http://"),
)
#: A line that only says whose work it is.
COPYRIGHT_LINE = r"(^|\n)[^\n]*(copyright ?(\(c\)|©|[0-9])|\(c\) ?[0-9]|© ?[0-9])[^\n]*"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Everything in ASCII but small letters and digits, and the usual signs beyond ASCII.
PUNCTUATION = r"[\x00-\x2F\x3A-\x60\x7B-\x7F“”‘’«»–—…•]+"

_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."""
_ISC_END = """THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
"""
_BSD_NAME = """
3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.
"""
_BSD_END = """
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
# Texts of public licences and of usual notices.
KNOWN = (
    ("MIT", "MIT License\n\n" + _MIT),
    ("MIT", _MIT),
    ("ISC", "ISC License\n\n" + _ISC + "\n\n" + _ISC_END),
    ("ISC", _ISC + "\n\n" + _ISC_END),
    ("0BSD", _ISC.replace(", provided that the above copyright notice and this permission notice appear in all copies", "") + "\n\n" + _ISC_END),
    ("BSD-2-Clause", _BSD + _BSD_END),
    ("BSD-3-Clause", _BSD + _BSD_NAME + _BSD_END),
    ("MIT", "Released under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("proprietary", "All rights reserved."),
)

# Digests of the canonical form of whole texts as their publishers give them, and of the terms alone where
# instructions for use follow them (with and without the line that ends them).
DIGESTS = (
    ("Apache-2.0", "6074c3536c43b739207170b87d1681477d0f07374ed3d862ba461334cce848e3"),  # whole
    ("Apache-2.0", "f70a2718f78121f2da77cd6afbffffbd668d7c1fd36c85a3ef121e83cb5f48fe"),  # terms
    ("Apache-2.0", "6aa661403864282a4d084f1551e8149a5f1a7b5e8b05b6db8e1a8a28d0badc64"),  # terms without end line
    ("Artistic-1.0-Perl", "08f1dc258c8f9e175155356aa1dd0dead8cfdec586bc1bb4c8b1452699a91702"),  # whole
    ("CC0-1.0", "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f"),  # whole
    ("GFDL-1.2", "15f6a8d360ffdecc988c29279c00f23e20de17f14f2a06572ab0d41de6e98b7b"),  # whole
    ("GFDL-1.3", "2d36daeff2ad303badb6dee8149748be25e22974dd468e1e8a55cf40f16fc01d"),  # whole
    ("GPL-1.0", "57b5701bbc49e33bbf15e6963f1dab77133171298a1829d7fb0b219c34fa3ff9"),  # whole
    ("GPL-1.0", "6375a768fd262bf5281905a9585411d2d0fb4ea15cb08cfcba49f73fedb82abc"),  # terms
    ("GPL-1.0", "89f75ffda938e788be38679f9f83e317c2a03398fccf03ee60505d44d1bf9f70"),  # terms without end line
    ("GPL-2.0", "75279e90b9b3146efccb6551ba7cdfc901d47aa8ce25d607b3da9b16eefa8c93"),  # whole
    ("GPL-2.0", "e1270b653c300290e7c039142bccb8776f9b5d14e8a05bc4e87dc7d1614a3b34"),  # terms
    ("GPL-2.0", "6d332dc4c3c5293a73c6c9da402f9bbc970b3bb1eb472f577e00580573469808"),  # terms without end line
    ("GPL-3.0", "739a8c73314d63afb8d0557ca44fd59f847001dc2636aed2936ff1c22ea82104"),  # whole
    ("GPL-3.0", "ac6b52d57c0104e687039148f7b8e370e04c9bb5705bb786f8ef814eb65e8636"),  # terms
    ("GPL-3.0", "092a7f3b82e6c22949b46388bca99e725b6e756f1c2b1e3f575447fbd44b6191"),  # terms without end line
    ("LGPL-2.0", "e4deecd0730802431ad09f00ae3793f3703c8e4dba639586545d9f958405614d"),  # whole
    ("LGPL-2.0", "504542bce5421b0f5a7e63ddb55443ccb300b27a65ba6bfc1370fed16a3af260"),  # terms
    ("LGPL-2.0", "430627da7218a92ab4a6d75d5140cdb70ee750be7a53f913299b37e0d1b0eea2"),  # terms without end line
    ("LGPL-2.1", "d3826e4e563a04a354453ff139a32b19d6c3fe283f518eb566107c54e18cd01f"),  # whole
    ("LGPL-2.1", "48d2010e70a815a564f914b0c7c1e80d7a6843793348fed3684c957112fe0aa4"),  # terms
    ("LGPL-2.1", "bf2f0c6bf1c47b3b1e3cbedeefecddd1e7db21d1919858d45c2f918efaf426df"),  # terms without end line
    ("LGPL-3.0", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),  # whole
    ("MPL-1.1", "469a6324726e3318515c938121859a1acfaba5d131d662968839e23a92b8a873"),  # whole
    ("MPL-2.0", "6fedd8db6adb0e102fc0f69b9e1501d2edaf25940e34910831cab46f9f5d4e4d"),  # whole
    ("Unlicense", "e2380bdfe57ca73b01d0b1848a4ee630998d729b260e63082b9267100b4a7229"),  # whole
)


def canonical(text: Column) -> Column:
    """A-Z lowered, copyright lines gone, spellings united, punctuation and white space single blanks."""
    out = F.translate(text, _UPPER, _LOWER)
    out = F.regexp_replace(out, COPYRIGHT_LINE, "")
    for old, new in SPELLINGS:
        out = F.replace(out, F.lit(old), F.lit(new))
    return F.trim(F.regexp_replace(out, PUNCTUATION, " "))


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


def known_digests(spark: SparkSession, known=KNOWN, digests=DIGESTS) -> DataFrame:
    """digest, licence: one row per digest, the first of equal ones."""
    rows = spark.createDataFrame([(n, k, t) for n, (k, t) in enumerate(known)], "n int, licence string, text string")
    rows = rows.select("n", "licence", digest(F.col("text")).alias("digest"))
    if digests:
        rows = rows.unionByName(spark.createDataFrame([(len(known) + n, k, d) for n, (k, d) in enumerate(digests)], "n int, licence string, digest string"))
    return rows.groupBy("digest").agg(F.min_by("licence", "n").alias("licence"))


def scan(docs: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """Per row of ``docs``: doc_id, canonical_digest, licence (null if the whole text is no known one).

    ``known`` has digest and licence, one row per digest; the default are the texts of
    public licences, and usual notices. It is joined by a hash join that Spark
    broadcasts only if it is small. A null text has a null digest; a text without
    letters and digits has the digest of nothing and no licence. Repeated rows
    are scanned each; an empty table gives an empty result.
    """
    known = known_digests(docs.sparkSession) if known is None else known
    held = docs.select("doc_id", digest(F.col("text")).alias("canonical_digest"))
    empty = F.sha2(F.lit(""), 256)
    match = (F.col("canonical_digest") == F.col("digest")) & (F.col("digest") != empty)
    return held.join(known, match, "left").select("doc_id", "canonical_digest", "licence")


def oracle_sql() -> str:
    """The same for DuckDB."""

    def text(value: str) -> str:
        return "'" + value.replace("'", "''") + "'"

    def expression(column: str) -> str:
        out = f"translate({column}, '{_UPPER}', '{_LOWER}')"
        out = f"regexp_replace({out}, {text(COPYRIGHT_LINE)}, '', 'g')"
        for old, new in SPELLINGS:
            out = f"replace({out}, {text(old)}, {text(new)})"
        return f"sha256(trim(regexp_replace({out}, {text(PUNCTUATION)}, ' ', 'g')))"

    rows = ", ".join(f"({n}, {text(k)}, {text(t)})" for n, (k, t) in enumerate(KNOWN))
    digests = ", ".join(f"({len(KNOWN) + n}, {text(k)}, {text(d)})" for n, (k, d) in enumerate(DIGESTS))
    return f"""
        WITH given AS (SELECT n, licence, {expression("t")} AS digest FROM (VALUES {rows}) v(n, licence, t) UNION ALL SELECT n, licence, digest FROM (VALUES {digests}) w(n, licence, digest)),
        known AS (SELECT digest, arg_min(licence, n) AS licence FROM given GROUP BY 1)
        SELECT d.doc_id, {expression("d.text")} AS canonical_digest, k.licence
        FROM documents d LEFT JOIN known k ON {expression("d.text")} = k.digest AND k.digest <> sha256('')
    """
