"""Licence scan by canonical digest lookup.

A text is made canonical: lower case, copyright lines dropped, equivalent spellings made
one, everything but letters and digits turned into single spaces. The sha-256 of the
whole canonical text is looked up, by a hash join, among the digests of known licence texts made canonical alike. The
same lookup of each single line finds licence notices inside other texts.

Known texts are a table (license_id, text), a handful of rows that is broadcast; pass your own to scan for more.
Null and empty texts, and texts that are nothing but punctuation, match nothing; of several
licences with one canonical text the least id is given; repeated rows are
looked up each for themselves; texts of any length are read whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_of

# Spellings that count as one, after lower-casing, in pairs of (found, written).
SPELLINGS = (
    ("acknowledgement", "acknowledgment"), ("analogue", "analog"), ("analyse", "analyze"), ("artefact", "artifact"), ("authorisation", "authorization"),
    ("authorised", "authorized"), ("calibre", "caliber"), ("cancelled", "canceled"), ("capitalisations", "capitalizations"), ("catalogue", "catalog"),
    ("categorise", "categorize"), ("centre", "center"), ("copyright holder", "copyright owner"), ("emphasised", "emphasized"), ("favour", "favor"),
    ("favourite", "favorite"), ("fulfil ", "fulfill "), ("fulfilment", "fulfillment"), ("initialise", "initialize"), ("judgement", "judgment"),
    ("labelling", "labeling"), ("labour", "labor"), ("licence", "license"), ("maximise", "maximize"), ("modelled", "modeled"), ("modelling", "modeling"),
    ("noncommercial", "non commercial"), ("offence", "offense"), ("optimise", "optimize"), ("organisation", "organization"), ("organise", "organize"),
    ("practise", "practice"), ("programme", "program"), ("realise", "realize"), ("recognise", "recognize"), ("signalling", "signaling"), ("sub license", "sublicense"),
    ("utilisation", "utilization"), ("whilst", "while"), ("wilful", "willful"), ("https", "http"), ("merchantability", "merchantability"),
)

# Texts of public licences and the notices that stand for longer ones.
_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD_BEGIN = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
"""
_BSD_THIRD = """
3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.
"""
_BSD_END = """
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_ZLIB = """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.

Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:

1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.

2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.

3. This notice may not be removed or altered from any source distribution."""
KNOWN = (
    ("MIT", _MIT), ("MIT", "MIT License\n\n" + _MIT), ("MIT", "The MIT License (MIT)\n\n" + _MIT), ("MIT", "Released under the MIT License."), ("MIT", "Licensed under the MIT License."),
    ("ISC", _ISC), ("ISC", "ISC License\n\n" + _ISC),
    ("BSD-2-Clause", _BSD_BEGIN + _BSD_END), ("BSD-2-Clause", "BSD 2-Clause License\n\n" + _BSD_BEGIN + _BSD_END),
    ("BSD-3-Clause", _BSD_BEGIN + _BSD_THIRD + _BSD_END), ("BSD-3-Clause", "BSD 3-Clause License\n\n" + _BSD_BEGIN + _BSD_THIRD + _BSD_END),
    ("Zlib", _ZLIB), ("Zlib", "zlib License\n\n" + _ZLIB),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at\n\n    http://www.apache.org/licenses/LICENSE-2.0\n\nUnless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("GPL-2.0-only", "This work is licensed under the GNU General Public License, version 2."), ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3."),
    ("LGPL-3.0-only", "This work is licensed under the GNU Lesser General Public License, version 3."), ("AGPL-3.0-only", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    *((f"CC-{kind.upper().replace(' ', '-')}-{version}", f"Licensed under CC {kind.upper()} {version}.") for kind in ("by", "by-sa", "by-nc", "by-nd", "by-nc-sa", "by-nc-nd") for version in ("3.0", "4.0")),
    *((f"CC-{kind.upper()}-{version}", f"This work is licensed under CC {kind.upper()} {version}.") for kind in ("by", "by-sa", "by-nc", "by-nd", "by-nc-sa", "by-nc-nd") for version in ("3.0", "4.0")),
    ("CC0-1.0", "Licensed under CC0 1.0."),
)

#: Digests of canonical whole texts of longer licences; where a text ends before its appendix, or before the words that end its terms, one of each.
KNOWN_DIGESTS = (
    ("Apache-2.0", "e87dea5078ce2faaea46d3475af18d30a5c0ac0f09425b60b3e0c6569f72f8d2"),
    ("Apache-2.0", "f45538b138cf9aea39fa205de037a0bede8305e68281650e7ab809a8b3ebb2f0"),
    ("Apache-2.0", "37599287c15c2f2ec060c3c3b55bdf69e3bc7a8aeeb9cd57e18800088789538a"),
    ("Artistic-1.0-Perl", "64e91f5cc481723b420f8e1ecf131ec7eba02da96cf0a78bb4b764fb30984f7a"),
    ("CC0-1.0", "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f"),
    ("GFDL-1.2-only", "c98e40efc6862c9be30915c75f49d704d06c4295eeee2bf5d221d9a5191e6b8a"),
    ("GFDL-1.3-only", "3238bf8a488349f6890209ed66942daa5c08256ad83b888cf417fbafcf0ceeaf"),
    ("GPL-1.0-only", "563aa819aa634f9698b263e285a0ef92b5388d22a13d9d829e3fd461737efbed"),
    ("GPL-1.0-only", "6c07dfb5e6ddc39fe93ae803d39b67367c21b50207b645111c04cd08cb283d70"),
    ("GPL-1.0-only", "3c796b04cfbd58d45e505bbfd656f39ed02b0e66f4b7768a6c92eb29931304c8"),
    ("GPL-2.0-only", "b48cdfd78fee492e1516a977f893a8b9b450447a909137054254b44ed775bcbf"),
    ("GPL-2.0-only", "f79b9e516923cc213c21d12fd8a51b4067992b2728a442e31fd53d078dd25632"),
    ("GPL-2.0-only", "b1a13b5262988058eb24fa2ecc2451ae813514d152b9361d66a115e43a210bf9"),
    ("GPL-3.0-only", "ce9b25a32fc0f53f6d32e74db713431d7d3f8f6d29bb4612998ff065cd901b18"),
    ("GPL-3.0-only", "2f5326aa8a00f9aaec5990337239231da07ca0fa219229d7bd0c79afd3cfbe60"),
    ("GPL-3.0-only", "308355c3080aa33279eaa8f75a1f1e6758b7972f216f60053639c192668d2dc1"),
    ("LGPL-2.0-only", "8e8ffd5752111302160e6ee7d7d229c3ff9fc6431363cfc44be8cfd0f64c24c6"),
    ("LGPL-2.0-only", "7d5246cc24a9d78fffd01a07fbc2e71edd1e94ad8d403f3180a4cf5fef43d389"),
    ("LGPL-2.0-only", "3ea7beb964a4396aa5ad75de90dd58ff01913b237f397517e8563b7acf07d87c"),
    ("LGPL-2.1-only", "5ce6fa0934cb8db1e96d36322f81fd98d11cc658ec86c71b9519d9c723a13041"),
    ("LGPL-2.1-only", "65484d3c9f900f96945bd4e6c5397aaa24f93bdc8f720eae06fbd377c62cfe97"),
    ("LGPL-2.1-only", "9c2c2afdce244f7835e438f43966f864ce47d82ebd6316bbcb123927f3280e30"),
    ("LGPL-3.0-only", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", "cbbde7eeab9b4d180dc00b34252f800e97fb1cddbab38ed8c0c73b956dc2cbf6"),
    ("MPL-2.0", "f82071285728ca3ec7685ee9bc4acdae0b8267142a4d20b8f1805eabedb4a98a"),
)

# Words after "copyright" that go on with a sentence instead of naming a holder.
_NO_HOLDER = r"notices?|statements?|disclaimers?|holders?|owners?|licen[cs]es?|licen[cs]ed|laws?|and|or|in|is|as|of|on|to|by|for|if|are|was|has|have|may|must|shall|will|can|not|that|which|with|under|rights?|protection|protected|treaty|treaties|information|permission|permissions|interest|interests|work|works|status|file|files|act|infringement|claims?|term|terms"
#: A line that only names who holds a copyright: with a sign or a year anywhere in it, or with a name of up to eight words that ends a paragraph or is followed by another such line.
COPYRIGHT_LINE = (
    r"(?m)^[^\p{L}\p{N}\n]*(?:copyright\b[^\p{L}\p{N}\n]*(?:\(c\)|©|\d{4})|\(c\)\s*(?:copyright\b|\d{4})|©)[^\n]*$|^[^\p{L}\p{N}\n]*all rights reserved\.?[^\p{L}\p{N}\n]*$"
    rf"|^[^\p{{L}}\p{{N}}\n]*copyright(?![-\w])[^\p{{L}}\p{{N}}\n]*(?!(?:{_NO_HOLDER})\b)\p{{L}}(?:[^\n]{{0,200}}\b(?:19|20)\d\d\b[^\n]{{0,200}}"
    r"|[^\s]*(?:[ \t]+[^\s]+){0,7}[ \t]*(?=\n\s*\n|\s*\z|\n[^\p{L}\p{N}\n]*(?:copyright|all rights reserved)\b))$"
)


def canonical(text: Column) -> Column:
    """The canonical form of a text."""
    out = F.regexp_replace(F.lower(text), "\r\n?", "\n")
    out = F.regexp_replace(out, COPYRIGHT_LINE, " ")
    out = F.trim(F.regexp_replace(out, r"[^\p{L}\p{N}]+", " "))
    return spelled(out)


#: What each known line holds.
LINE_MARKS = r"licen[cs]e|licensed|copyright|permission|warrant|redistribut|\bcc"


def spelled(text: Column) -> Column:
    """Spellings made one, wherever they stand."""
    out = text
    for found, written in SPELLINGS:
        if found != written:
            out = F.replace(out, F.lit(found), F.lit(written))
    return out


def digest(text: Column) -> Column:
    return F.sha2(canonical(text).cast("binary"), 256)


def text_digests(rows: DataFrame) -> DataFrame:
    """(digest, license_id) of known texts (license_id, text)."""
    own = rows.withColumn("plain", canonical(F.col("text"))).where("plain <> ''")
    return own.select(F.sha2(F.col("plain").cast("binary"), 256).alias("digest"), "license_id")


def known_digests(spark: SparkSession, known=KNOWN, digests=KNOWN_DIGESTS) -> DataFrame:
    rows = text_digests(spark.createDataFrame(list(known), "license_id string, text string"))
    whole = spark.createDataFrame(list(digests), "license_id string, digest string").select("digest", "license_id")
    return rows.unionByName(whole).groupBy("digest").agg(F.min("license_id").alias("license_id"))


def scan(docs: DataFrame, known: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_digest, license_id, line_licenses), one row per row of ``docs``.

    ``license_id`` is null unless the whole text is a known one; ``line_licenses``
    lists the licences of single lines, in order and joined by commas. ``known`` is a
    table (license_id, text), or (license_id, digest) of canonical texts; every line is looked up in it. The known lines
    that come with this module all hold one of ``LINE_MARKS``, so with them lines without one are not looked up.
    """
    marked = known is None
    if known is None:
        known = known_digests(docs.sparkSession)
    else:
        own = known.select("digest", "license_id") if "digest" in known.columns else text_digests(known)
        known = own.groupBy("digest").agg(F.min("license_id").alias("license_id"))
    known = F.broadcast(known)  # a table of known texts
    # One row of known lines by digest: a map lookup keeps every document in its row.
    as_map = known.agg(F.map_from_entries(F.collect_list(F.struct("digest", "license_id"))).alias("by_digest"))
    own = docs.select(F.col(id_col).alias("doc_id"), text_of(text_col).alias("text")).withColumn("text_digest", digest(F.col("text")))
    lines = F.split("text", "\r\n|\r|\n")
    if marked:
        lines = F.filter(lines, lambda x: F.lower(x).rlike(LINE_MARKS))
    found = F.filter(F.transform(lines, lambda x: F.element_at("by_digest", digest(x))), lambda x: x.isNotNull())
    return (
        own.join(known.select(F.col("digest").alias("text_digest"), "license_id"), "text_digest", "left")
        .join(F.broadcast(as_map))  # one row
        .select("doc_id", "text_digest", "license_id", F.array_join(found, ",").alias("line_licenses"))
    )
