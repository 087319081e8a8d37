"""Licences as their publishers print them: whole texts in ``texts``, headers and SPDX lines."""

from pathlib import Path

import pytest

from wordset.llm import licenses

TEXTS = {p.stem: p.read_text() for p in (Path(__file__).parent / "texts").glob("*.txt")}
APACHE = """# Licensed under the Apache License, Version 2.0 (the "License");
# you may not use this file except in compliance with the License.
# You may obtain a copy of the License at
#
#     http://www.apache.org/licenses/LICENSE-2.0
#
# Unless required by applicable law or agreed to in writing, software
# distributed under the License is distributed on an "AS IS" BASIS,
# WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
# See the License for the specific language governing permissions and
# limitations under the License.
"""
GPL = """/* This program is free software{0} you can redistribute it and/or modify
 * it under the terms of the GNU General Public License as published by
 * the Free Software Foundation{1} either version {2} of the License, or
 * (at your option) any later version. */
"""
MPL = "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0. If a copy of the MPL was not distributed with this\nfile, You can obtain one at https://mozilla.org/MPL/2.0/."
CASES = [
    (APACHE, "Apache-2.0", "101,102,103,104"),
    (GPL.format(":", ",", 3), "GPL-3.0-or-later", "302,303"),
    (GPL.format(";", ";", 2), "GPL-2.0-or-later", "302,304"),
    (MPL, "MPL-2.0", "601"),
    ("// SPDX-License-Identifier: Apache-2.0\nint x;", "Apache-2.0", "902"),
    ("SPDX-License-Identifier: MIT", "MIT", "903"),
    ("SPDX-License-Identifier: GPL-3.0-only", "GPL-3.0-only", "904"),
    ("SPDX-License-Identifier: BSD-3-Clause", "BSD-3-Clause", "905"),
    ("SPDX-License-Identifier: GPL-2.0+", "GPL-2.0-or-later", "908"),
    ("SPDX-License-Identifier: MIT OR Apache-2.0", "Apache-2.0,MIT", "903,902"),
    ("released under the\n\nMIT license", "", ""),
    ("not released under the MIT license", "", ""),
]


@pytest.fixture(scope="module")
def found(spark):
    texts = list(TEXTS.values()) + [c[0] for c in CASES]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r for r in sorted(licenses.scan(df).collect())]


def test_whole_texts(found):
    got = {name: set(r.licenses.split(",")) - {"LicenseRef-all-rights-reserved"} for name, r in zip(TEXTS, found, strict=False)}
    assert len(got) == 7 and got == {name: {name} for name in TEXTS}


def test_headers(found):
    assert [(r.licenses, r.sids) for r in found[len(TEXTS) :]] == [c[1:] for c in CASES]


def test_lines_between_wrapped_sentences(spark):
    df = spark.createDataFrame([(1, "Released under the\nMIT License.\nother\nwords\nAll rights\nreserved.")], "doc_id long, text string")
    assert [(r.sids, r.gaps) for r in licenses.scan(df).collect()] == [("201,901", 2)]
