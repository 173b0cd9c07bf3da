"""Notices as they are really written: hard-wrapped, in comments, with lead-ins."""

import textwrap

import pytest

from textgroups.llm import license_scan

MIT = ["Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."]
APACHE = ["Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at", "    http://www.apache.org/licenses/LICENSE-2.0"]
GPL = ["This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE."]
BSD = ["1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.", "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.", "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."]


@pytest.mark.parametrize("mark", ["", "# ", " * ", "// "])
@pytest.mark.parametrize("width", [70, 80])
def test_wrapped_notices(spark, mark, width):
    def write(paragraphs):
        return "\n".join(mark + line for p in paragraphs for line in [*textwrap.wrap(p, width), ""])

    texts = [write(MIT), write(APACHE), write(GPL), write(BSD), write(BSD[:2]), "x.\nThis project is released under the MIT License.", write(["Permission is hereby granted, free of charge."]), "This is released under\n\nthe MIT License."]
    d = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r["licenses"] for r in license_scan.scan(d).collect()}
    assert got == {0: ["MIT"], 1: ["Apache-2.0"], 2: ["GPL-3.0"], 3: ["BSD-3-Clause"], 4: ["BSD-2-Clause"], 5: ["MIT"], 6: [], 7: []}


LGPL = ["This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.", "This library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the GNU Lesser General Public License for more details."]
AGPL = [GPL[0].replace("GNU General", "GNU Affero General"), GPL[1]]
GPL2 = [GPL[0].replace("version 3", "version 2").replace("software:", "software;"), GPL[1]]
MPL = ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."]
ISC = ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."]
CC = ["This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."]


@pytest.mark.parametrize("mark", ["", "# ", " * "])
def test_more_notices_and_identifiers(spark, mark):
    def write(paragraphs):
        return "\n".join(mark + line for p in paragraphs for line in [*textwrap.wrap(p, 72), ""])

    texts = {"LGPL-2.1": write(LGPL), "AGPL-3.0": write(AGPL), "GPL-2.0": write(GPL2), "MPL-2.0": write(MPL), "ISC": write(ISC), "CC-BY-SA-4.0": write(CC)}
    for n in ("MIT", "Apache-2.0", "GPL-3.0-or-later", "BSD-3-Clause"):
        texts[n] = f"{mark}SPDX-License-Identifier: {n}\n\nint main() {{}}\n"
    d = spark.createDataFrame([(n, i, t) for i, (n, t) in enumerate(texts.items())], "name string, doc_id long, text string")
    got = {r["doc_id"]: r["licenses"] for r in license_scan.scan(d).collect()}
    assert got == {i: [n] for i, n in enumerate(texts)}


def test_noise_before_a_sentence(spark):
    """A sentence behind thousands of other characters is found like any other."""
    d = spark.createDataFrame([(0, "*" * 5000 + "Released under the MIT License."), (1, "x " * 5000 + "\nReleased under the MIT License.\n" + "y " * 5000)], "doc_id long, text string")
    assert all(r["licenses"] == ["MIT"] for r in license_scan.scan(d).collect())
