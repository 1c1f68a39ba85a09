"""Licence scans by canonical digest, in DataFrame functions only.

An entire text is normalised - letter case, copyright lines, equivalent spellings, punctuation and
white space - and its digest is joined with digests of known licence texts.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Spellings that count as equal (the left becomes the right), applied in this order.
SPELLINGS = [
    ("licence", "license"), ("sub-license", "sublicense"), ("sub license", "sublicense"), ("favour", "favor"),
    ("organisation", "organization"), ("authoris", "authoriz"), ("recognis", "recogniz"), ("judgement", "judgment"),
    ("acknowledgement", "acknowledgment"), ("fulfil ", "fulfill "), ("non-infringement", "noninfringement"),
    ("non infringement", "noninfringement"), ("copyright owner", "copyright holder"), ("per cent", "percent"), ("https:", "http:"),
]
#: A copyright statement has a sign or a year; a line that only begins with the word (as in wrapped texts) stays.
COPYRIGHT_LINE = r"(?m)^[ \t*#/;-]*(?:copyright\b[^\n]*(?:\(c\)|©|(?:19|20)[0-9][0-9]|[\[<{(]y)|\(c\)|©|all rights reserved)[^\n]*$"
PUNCTUATION = "!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~“”‘’–—«»©"
BLANKS = r"[\x20\x09-\x0D]+"

_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR "
    "ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH "
    "THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_ISC = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC_END = (
    '\n\nTHE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES '
    "OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY "
    "DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, "
    "ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_TERMS = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n\n"
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n\n"
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution.\n\n"
)
_BSD_NAME = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n\n"
_BSD_END = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, '
    "THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS "
    "BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE "
    "GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT "
    "LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_ZLIB = (
    "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the "
    "use of this software.\n\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and "
    "redistribute it freely, subject to the following restrictions:\n\n1. The origin of this software must not be misrepresented; you must not claim that you wrote "
    "the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.\n\n"
    "2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.\n\n"
    "3. This notice may not be removed or altered from any source distribution."
)
_UNLICENSE = (
    "This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, "
    "either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\n\nIn jurisdictions that recognize copyright "
    "laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of "
    "the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and "
    'future rights to this software under copyright law.\n\nTHE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO '
    "THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
    "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
#: Texts and notices of public licences, each with and without its heading; more come as a table.
KNOWN = {
    "BSD-2-Clause": "BSD 2-Clause License\n\nCopyright (c) year holder\n\n" + _BSD_TERMS + _BSD_END,
    "BSD-3-Clause": "BSD 3-Clause License\n\nCopyright (c) year holder\n\n" + _BSD_TERMS + _BSD_NAME + _BSD_END,
    "Zlib": "zlib License\n\nCopyright (c) year holder\n\n" + _ZLIB,
    "Unlicense": "The Unlicense\n\n" + _UNLICENSE,

    "MIT": "MIT License\n\nCopyright (c) year holder\n\nPermission is hereby granted, free of charge, to any person obtaining a copy of this software and "
    'associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, '
    "copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished "
    "to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or "
    "substantial portions of the Software.\n\n" + _WARRANTY,
    "ISC": f"ISC License\n\nCopyright (c) year holder\n\n{_ISC}, provided that the above copyright notice and this permission notice appear in all copies." + _ISC_END,
    "0BSD": f"Zero-Clause BSD\n\n{_ISC}." + _ISC_END,
    "Apache-2.0 notice": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0 notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0 notice": "Licensed under CC BY-NC 4.0.",
}


def with_headings(known: dict[str, str]) -> list[tuple[str, str]]:
    """(license_id, text): each text as it is and, where a heading stands over it, without."""
    out = []
    for name, text in sorted(known.items()):
        out.append((name, text))
        heading, gap, rest = text.partition("\n\n")
        if gap and len(heading) < 60:
            out.append((name, rest))
    return out


def normalised(text: Column) -> Column:
    t = F.regexp_replace(F.regexp_replace(F.lower(text), COPYRIGHT_LINE, " "), BLANKS, " ")
    for a, b in SPELLINGS:
        t = F.replace(t, F.lit(a), F.lit(b))
    t = F.translate(t, PUNCTUATION, " " * len(PUNCTUATION))
    return F.trim(F.regexp_replace(t, BLANKS, " "))


def known_digests(spark: SparkSession, texts: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """(digest, license_id): one row a digest; equal digests keep the least name."""
    rows = texts if isinstance(texts, DataFrame) else spark.createDataFrame(with_headings(texts or KNOWN), "license_id string, text string")
    rows = rows.where("text IS NOT NULL").select(F.sha2(normalised(F.col("text")), 256).alias("digest"), "license_id")
    return rows.groupBy("digest").agg(F.min("license_id").alias("license_id"))


def scan(docs: DataFrame, known: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """(doc_id, digest, license_id) of every row; license_id null where the digest isn't known.

    Null texts have no digest and no licence; blank texts have the digest of the empty string,
    which no licence has. Repeated rows are kept. Known licences join by hash; a digest that many
    documents share meets one known row only. Texts of any length are taken whole, an empty table gives an empty result,
    other columns are ignored."""
    digests = known_digests(docs.sparkSession, known)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.sha2(normalised(F.col("text")), 256).alias("digest"))
    return rows.join(digests, "digest", "left").select("doc_id", "digest", "license_id")
