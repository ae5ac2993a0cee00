"""Every sentence of the table alone, and whole licence texts as they are wrapped in files."""

from hcube.llm import licences

ALONE = {
    "agpl": "GNU Affero General Public License", "lgpl3": "GNU Lesser General Public License, version 3", "lgpl21": "GNU Library General Public License version 2",
    "gpl3plus": "GNU General Public License, version 3 or any later", "gpl2plus": "GNU General Public License version 2 or (at your option) any later version",
    "gpl3": "GNU General Public License version 3", "gpl2": "GNU General Public License, version 2", "gplany": "the GNU General Public License",
    "apache2": "Licensed under the Apache License, Version 2.0", "apache-compliance": "you may not use this file except in compliance with the License",
    "apache-copy": "You may obtain a copy of the License at", "apache-asis": "software distributed under the License is distributed on an \"AS IS\" BASIS",
    "mit-short": "Released under the MIT license", "mit-grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software",
    "mit-notice": "The above copyright notice and this permission notice shall be included in all copies",
    "mit-asis": "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED",
    "isc-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose", "isc-asis": "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES",
    "bsd-grant": "Redistribution and use in source and binary forms, with or without modification", "bsd-source": "Redistributions of source code must retain the above copyright notice",
    "bsd-binary": "Redistributions in binary form must reproduce the above copyright notice", "bsd-noendorse": "Neither the name of X may be used to endorse or promote products",
    "bsd-asis": "THIS SOFTWARE IS PROVIDED BY X \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES", "mpl2": "Mozilla Public License, version 2.0", "epl2": "Eclipse Public License v2.0",
    "cc-by-nc-nd": "Shared under CC BY-NC-ND 4.0", "cc-by-nc-sa": "Attribution-NonCommercial-ShareAlike", "cc-by-nc": "Attribution-NonCommercial 4.0", "cc-by-nd": "CC BY-ND",
    "cc-by-sa": "Shared under CC BY-SA 4.0.", "cc-by": "Licensed under a Creative Commons Attribution", "cc0": "CC0 1.0", "unlicense": "This is free and unencumbered software released into the public domain.",
    "all-rights": "All rights reserved.", "liability": "IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM",
}
SPDX = {"apache2": "Apache-2.0", "mit": "MIT", "bsd3": "BSD-3-Clause", "bsd2": "BSD-2-Clause", "gpl3": "GPL-3.0", "gpl2": "GPL-2.0", "mpl2": "MPL-2.0"}


def test_each_sentence_alone_is_found(spark):
    alone = ALONE | {f"spdx-{k}": f"SPDX-License-Identifier {v}" for k, v in SPDX.items()}
    assert set(alone) == {k for k, _ in licences.SENTENCES}
    alone |= {" cc0": "public domain dedication", "  cc0": "Creative Commons Zero", " cc-by-nc": "CC-BY-NC", " cc-by-sa": "Attribution\nShareAlike".replace("\n", " - ")}
    df = spark.createDataFrame(list(enumerate(alone.values())), "doc_id long, text string")
    got = {r.doc_id: r.sentence_ids for r in licences.op7_licence_scan(df).collect()}
    assert {k: got[i] for i, k in enumerate(alone)} == {k: k.strip() for k in alone}


MIT = """MIT License

Copyright (c) 2020 Jane Roe

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.
"""
BSD = """Copyright (c) 2020, Jane Roe
All rights reserved.

Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation.
{more}
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS"
AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE
IMPLIED WARRANTIES OF MERCHANTABILITY ARE DISCLAIMED.
"""
NOENDORSE = """
3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.
"""
APACHE = """# Copyright 2020 Jane Roe
#
# Licensed under the Apache License, Version 2.0 (the "License");
# you may not use this file except in compliance with the License.
# You may obtain a copy of the License at
#
#     http://www.apache.org/licenses/LICENSE-2.0
#
# Unless required by applicable law or agreed to in writing, software
# distributed under the License is distributed on an "AS IS" BASIS,
# WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
"""
ISC = """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL
WARRANTIES WITH REGARD TO THIS SOFTWARE.
"""
GNU = """ * This program is free software; you can redistribute it and/or modify
 * it under the terms of the GNU {kind}General Public
 * License as published by the Free Software Foundation; {version}
"""
TEXTS = {
    "MIT": MIT, "BSD-2-Clause": BSD.format(more=""), "BSD-3-Clause": BSD.format(more=NOENDORSE), "Apache-2.0": APACHE, "ISC": ISC,
    "LGPL-2.1": GNU.format(kind="Lesser ", version="either\n * version 2.1 of the License, or (at your option) any later version."),
    "LGPL-3.0": GNU.format(kind="Lesser ", version="either\n * version 3 of the License, or (at your option) any later version."),
    "GPL-2.0-or-later": GNU.format(kind="", version="either version 2\n * of the License, or (at your option) any later version."),
    "GPL-3.0-or-later": GNU.format(kind="", version="either version 3 of the\n * License, or (at your option) any later version."),
    "GPL-2.0": GNU.format(kind="", version="version 2."), "GPL-3.0": GNU.format(kind="", version="version 3."), "AGPL-3.0": GNU.format(kind="Affero ", version="version 3."),
    "GPL": "Under the GNU General\nPublic License.", "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0.",
    "EPL-2.0": "made available under the terms of the\nEclipse Public License v2.0", "CC-BY": "This text is licensed under a Creative\nCommons Attribution 4.0 licence.",
    "CC-BY-SA": "Shared under CC\nBY-SA 4.0.", "CC-BY-NC": "Attribution-NonCommercial", "CC-BY-ND": "Attribution-\nNoDerivatives 4.0", "CC-BY-NC-SA": "CC BY-NC-SA", "CC-BY-NC-ND": "CC BY-NC-ND",
    "CC0-1.0": "CC0 1.0", "Unlicense": "This is free and unencumbered software released into\nthe Public Domain.",
}


def test_wrapped_texts_of_all_licences(spark):
    assert set(TEXTS) == {name for name, _ in licences.RULES}
    more = {f"SPDX-License-Identifier: {v}\nCopyright 2020 X\nAll rights reserved": v for v in SPDX.values()}
    liable = "IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR\nCONTRIBUTORS BE LIABLE FOR ANY DAMAGES.\n"
    more |= {MIT + liable: "MIT", BSD.format(more="") + liable: "BSD-2-Clause", BSD.format(more=NOENDORSE) + "\n" + liable: "BSD-3-Clause", ISC + liable: "ISC"}
    more |= {"\r\n".join(MIT.split("\n")): "MIT", MIT.replace("THE SOFTWARE IS", "Licence of X.\n\nTHE SOFTWARE IS"): "MIT"}
    texts = [*((v, k) for k, v in TEXTS.items()), *more.items()]
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(texts)], "doc_id long, text string")
    got = {r.doc_id: r for r in licences.op7_licence_scan(df).collect()}
    assert {(i, name): got[i].licences for i, (_, name) in enumerate(texts)} == {(i, name): name for i, (_, name) in enumerate(texts)}
    assert not any("liability" in r.leftover for r in got.values())
    assert all("all-rights" in got[i].leftover for i, (t, _) in enumerate(texts) if "All rights" in t)
