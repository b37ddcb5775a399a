"""Licence scans by canonical digests.

A text is put into a canonical form (case, punctuation, white space, copyright lines and equivalent
spellings removed), digested, and hash-joined as a whole to the digests of known licences. Licence
notices stand as lines inside other texts, so lines are digested and joined likewise. Built in are short
licences, digests of long ones, and notices made from names; other tables of licences can be passed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import broadcast_if_small, pick, stored, table

#: Spellings that licence texts use for the same word, canonical form last.
SPELLINGS = (("licence", "license"), ("sub license", "sublicense"), ("non commercial", "noncommercial"), ("acknowledgement", "acknowledgment"), ("organisation", "organization"), ("whilst", "while"), ("judgement", "judgment"), ("merchantibility", "merchantability"), ("per cent", "percent"), ("http ", "https "))
#: Whole texts of short licences, by identifier, without titles and copyright lines.
_AS_IS = "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
_GRANT = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so"
_AUTHOR = "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
_REDISTRIBUTION = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.\n"
_NO_NAMES = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n"
_DISCLAIMED = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
TEXTS = (
    ("MIT", "MIT License", f"{_GRANT}, subject to the following conditions:\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n{_AS_IS}"),
    ("MIT-0", "MIT No Attribution", f"{_GRANT}.\n{_AS_IS}"),
    ("ISC", "ISC License", f"Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\n{_AUTHOR}"),
    ("0BSD", "BSD Zero Clause License", f"Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n{_AUTHOR}"),
    ("BSD-2-Clause", "BSD 2-Clause License", f"{_REDISTRIBUTION}{_DISCLAIMED}"),
    ("BSD-3-Clause", "BSD 3-Clause License", f"{_REDISTRIBUTION}{_NO_NAMES}{_DISCLAIMED}"),
    ("Zlib", "zlib License", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:\n1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.\n3. This notice may not be removed or altered from any source distribution."),
    ("Unlicense", "The Unlicense", "This is free and unencumbered software released into the public domain.\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\nIn jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.\nFor more information, please refer to <https://unlicense.org>"),
    ("BSL-1.0", "Boost Software License - Version 1.0 - August 17th, 2003", "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:\nThe copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("FSFAP", "FSF All Permissive License", "Copying and distribution of this file, with or without modification, are permitted in any medium without royalty provided the copyright notice and this notice are preserved. This file is offered as-is, without any warranty."),
    ("WTFPL", "DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE", "Everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed as long as the name is changed.\nDO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE\nTERMS AND CONDITIONS FOR COPYING, DISTRIBUTION AND MODIFICATION\n0. You just DO WHAT THE FUCK YOU WANT TO."),
    ("Apache-2.0", "", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at\nhttp://www.apache.org/licenses/LICENSE-2.0\nUnless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("MPL-2.0", "", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
)
#: Digests of the canonical forms of long licences, as the Debian system carries their texts.
DIGESTS = (
    ("Apache-2.0", "769f6cd740fe13ac62c8d735e4f75a44231f944dc392325d819290d7fb6b07e1"),
    ("Artistic-1.0-Perl", "e963bc30f4d3c45f45030c34409ee37315564625649c1394e32bb5ddd99e01b2"),
    ("BSD-3-Clause-UC", "2f8c6e1fbad71537ccf82be397287a98faf8d21ae0d307d8d0201874cbb6705e"),
    ("CC0-1.0", "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f"),
    ("GFDL-1.2", "5a3b24c0d356ef8989faaaabae94f88aae352636c3cd36da5f5a76f39cd16b83"),
    ("GFDL-1.3", "9330d425b8d1073fd89f543fb54e3a4b4c91abbbcd9a5b933b57f3edc95832bd"),
    ("GPL-1.0", "eafda7cb5e995143f4d45ef2107eb160d6856afabed7c48b1b317303bc40a7e6"),
    ("GPL-2.0", "efe73660e5476cf0368fc0fc143f624ff9d1b73c4484b14a9969dd20c5786821"),
    ("GPL-3.0", "a8cd54d6683aa630f0b8d05d56184ad91dc486756da2df61c94d3e4e8d5ecb68"),
    ("LGPL-2.0", "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908"),
    ("LGPL-2.1", "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891"),
    ("LGPL-3.0", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", "3f0343dd4f3b064be36e0c6584737c9b7bb5c322721694563f9009e088ce96d1"),
    ("MPL-2.0", "9eab7902f21bef0326dee4ed0cae1402c781cbf1f8e3dbeed6fbe176d641bb13"),
)
#: Identifiers with the names under which notices cite them.
NAMES = (
    ("Apache-2.0", ("Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 License", "Apache-2.0")),
    ("MIT", ("MIT License",)),
    ("ISC", ("ISC License",)),
    ("BSD-2-Clause", ("BSD 2-Clause License", "Simplified BSD License")),
    ("BSD-3-Clause", ("BSD 3-Clause License", "New BSD License", "Modified BSD License")),
    ("0BSD", ("BSD Zero Clause License",)),
    ("Zlib", ("zlib License",)),
    ("BSL-1.0", ("Boost Software License, Version 1.0",)),
    ("MPL-2.0", ("Mozilla Public License 2.0", "Mozilla Public License, version 2.0")),
    ("EPL-2.0", ("Eclipse Public License 2.0", "Eclipse Public License - v 2.0")),
    ("GPL-2.0", ("GNU General Public License, version 2", "GNU General Public License v2.0", "GPLv2")),
    ("GPL-3.0", ("GNU General Public License, version 3", "GNU General Public License v3.0", "GPLv3")),
    ("LGPL-2.1", ("GNU Lesser General Public License, version 2.1", "LGPLv2.1")),
    ("LGPL-3.0", ("GNU Lesser General Public License, version 3", "LGPLv3")),
    ("AGPL-3.0", ("GNU Affero General Public License, version 3", "AGPLv3")),
    ("CC0-1.0", ("CC0 1.0", "CC0 1.0 Universal")),
    *((f"CC-{kind}-{v}", (f"CC {kind} {v}", f"CC-{kind}-{v}")) for kind in ("BY", "BY-SA", "BY-NC", "BY-ND", "BY-NC-SA", "BY-NC-ND") for v in ("2.0", "3.0", "4.0")),
)
#: How notices cite a name.
CITED = ("Licensed under the {}.", "Licensed under {}.", "Released under the {}.", "Released under {}.", "This work is licensed under the {}.", "This work is licensed under {}.", "This software is licensed under the {}.", "Distributed under the {}.", "Available under the {}.")


def known_texts() -> list[tuple[str, str]]:
    """(identifier, text) of the built-in notices and short licences; licences with and without their titles."""
    out = [(i, t) for i, title, text in TEXTS for t in dict.fromkeys((text, f"{title}\n{text}"))]
    for i, names in NAMES:
        out.append((i, f"SPDX-License-Identifier: {i}"))
        out += [(i, form.format(name)) for name in names for form in CITED]
    return out


def canonical(text: Column) -> Column:
    """The canonical form: null stays null; texts without letters or digits become empty."""
    t = F.regexp_replace(text, r"(?im)^[ \t]*(?:copyright|\(c\)|©)[^\n]*(?:[0-9]{4}|<year>|\[year\])[^\n]*$|^[ \t]*all rights reserved\.?[ \t]*$", "")
    t = F.regexp_replace(F.lower(t), r"[^\p{L}\p{N}]+", " ")
    for a, b in SPELLINGS:
        t = F.replace(t, F.lit(a), F.lit(b))
    return F.trim(t)


def digest(text: Column) -> Column:
    """SHA-256 of the canonical form; null for null and for forms without content."""
    form = canonical(text)
    return F.when(form != "", F.sha2(form, 256))


def known_licenses(spark: SparkSession, texts: DataFrame | None = None) -> DataFrame:
    """digest, license_id, length (of the canonical form; null where only the digest is known).

    Without texts (license_id, text), the built-in licences. Of two identifiers with one digest the smaller counts.
    """
    own = spark.createDataFrame(known_texts(), "license_id string, text string") if texts is None else texts.select("license_id", "text")
    rows = own.select(F.col("license_id"), digest(F.col("text")).alias("digest"), F.length(canonical(F.col("text"))).alias("length"))
    if texts is None:
        rows = rows.union(spark.createDataFrame([(i, d, None) for i, d in DIGESTS], "license_id string, digest string, length int"))
    return rows.filter("digest is not null").groupBy("digest").agg(F.min("license_id").alias("license_id"), F.max("length").alias("length"))


def licenses_in(spark: SparkSession, folder: str) -> DataFrame:
    """(license_id, text) of a folder of licence texts, one a file, each named by its identifier."""
    files = spark.read.text(folder, wholetext=True).select("value", F.col("_metadata.file_name").alias("name"))
    return files.select(F.regexp_replace("name", r"\.(txt|md)$", "").alias("license_id"), F.col("value").alias("text"))


#: Largest number of distinct lengths of known forms by which lines are told apart before they are digested.
MOST_LENGTHS = 10_000


def license_scan(docs: DataFrame, licenses: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, text_digest, license_id, notices for each row of docs.

    license_id is the known licence that the whole text is (null if none), notices the sorted distinct licences
    that are whole lines of it. Null and empty texts have no digest, no licence and no notices. Repeated rows and
    null keys are kept. Extra columns are ignored; licenses has digest, license_id and, if known, length: a line
    whose canonical form has no known length is no notice and is not digested. Forms without a length are whole
    texts only.
    """
    rows = pick(docs, key, text).toDF("key", "text")
    known = stored(licenses.select("digest", "license_id", "length"), "licences")
    found = [r["length"] for r in known.filter("length is not null").select("length").distinct().limit(MOST_LENGTHS + 1).collect()]
    forms = F.transform(F.split(F.coalesce("text", F.lit("")), "\n"), canonical)
    if len(found) <= MOST_LENGTHS:
        forms = F.filter(forms, lambda f: F.length(f).isin(found))
    forms = F.filter(F.array_distinct(forms), lambda f: f != "")
    rows = rows.select("key", digest(F.col("text")).alias("text_digest"), F.transform(forms, lambda f: F.sha2(f, 256)).alias("lines"))
    rows = stored(rows.withColumn("row", F.monotonically_increasing_id()), "digests")
    count = known.count()
    notices = broadcast_if_small(known.filter("length is not null").select("digest", "license_id"), 100, count)
    noticed = rows.select("row", F.explode("lines").alias("digest")).join(notices, "digest").groupBy("row").agg(F.array_sort(F.collect_set("license_id")).alias("notices"))
    texts = broadcast_if_small(known.select(F.col("digest").alias("text_digest"), "license_id"), 100, count)
    whole = rows.join(texts, "text_digest", "left").join(noticed, "row", "left")
    return whole.select(F.col("key").alias(key), "text_digest", "license_id", F.coalesce("notices", F.array().cast("array<string>")).alias("notices"))


def op10_license_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(table(spark, sf_dir, "documents"), known_licenses(spark))
