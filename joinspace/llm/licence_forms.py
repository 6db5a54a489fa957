"""Whole licence texts, their titles and the standard header forms of source files, as templates of `licenses`.

A form is (SPDX identifier, key words, text). A passage has a form only if it holds all its key words, which tell versions and
relatives apart; the first key word is the rarest one. Texts are the files of `licence_texts`.
"""

from __future__ import annotations

from pathlib import Path

TEXTS = Path(__file__).with_name("licence_texts")

#: Fixed value: key words of the whole texts.
WHOLE = {
    "Apache-2.0": "apache license 2",
    "BSD-2-Clause": "redistributions redistribution disclaimer",
    "BSD-3-Clause": "redistributions redistribution disclaimer neither endorse",
    "CC0-1.0": "cc0 creative commons",
    "GPL-2.0": "gnu general public 2 1991",
    "GPL-3.0": "gnu general public 3 2007",
    "ISC": "hereby permission fee",
    "LGPL-2.1": "lesser gnu general public 2 1",
    "LGPL-3.0": "lesser gnu general public 3",
    "MIT": "hereby permission granted sublicense",
    "MPL-2.0": "mozilla public 2",
}


def _gnu(what: str, name: str, version: str) -> str:
    return f"{what} is free software: you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation, either version {version} of the License, or (at your option) any later version."


def _only(what: str, name: str, version: str) -> str:
    return f"{what} is free software; you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation; version {version} of the License."


#: Titles and header paragraphs.
HEADERS = [
    ("Apache-2.0", "apache license 2", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/"),
    ("Apache-2.0", "apache license 2", "Apache License, Version 2.0"),
    ("Apache-2.0", "apache license 2", "Apache License 2.0"),
    ("Apache-2.0", "apache license 2", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at'),
    ("Apache-2.0", "apache license 2", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("Apache-2.0", "apache license asf 2", 'Licensed to the Apache Software Foundation (ASF) under one or more contributor license agreements. See the NOTICE file distributed with this work for additional information regarding copyright ownership. The ASF licenses this file to You under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at'),
    ("BSD-2-Clause", "bsd 2 clause license", "BSD 2-Clause License"),
    ("BSD-3-Clause", "bsd 3 clause license", "BSD 3-Clause License"),
    ("BSD-3-Clause", "bsd style license", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("CC-BY-4.0", "commons creative attribution 4", "Creative Commons Attribution 4.0 International Public License"),
    ("CC-BY-4.0", "commons creative attribution 4", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "noncommercial commons creative 4", "Creative Commons Attribution-NonCommercial 4.0 International Public License"),
    ("CC-BY-NC-4.0", "noncommercial commons creative 4", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "cc0 1 universal", "CC0 1.0 Universal"),
    ("ISC", "isc license", "ISC License"),
    ("ISC", "hereby permission fee", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MIT", "mit license", "MIT License"),
    ("MIT", "mit license", "The MIT License (MIT)"),
    ("MIT", "mit license", "Licensed under the MIT license."),
    ("MIT", "mit license", "This project is licensed under the terms of the MIT license. See the LICENSE file in the project root."),
    ("MIT", "hereby permission granted sublicense", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'),
    ("MPL-2.0", "mozilla public license 2", "Mozilla Public License Version 2.0"),
    ("MPL-2.0", "mozilla public license 2", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
]
for _id, _name, _key, _version, _date in (
    ("AGPL-3.0", "GNU Affero General Public License", "affero 3", "3", "19 November 2007"),
    ("GPL-2.0", "GNU General Public License", "gnu general public 2", "2", "June 1991"),
    ("GPL-3.0", "GNU General Public License", "gnu general public 3", "3", "29 June 2007"),
    ("LGPL-2.1", "GNU Lesser General Public License", "lesser gnu 2 1", "2.1", "February 1999"),
    ("LGPL-3.0", "GNU Lesser General Public License", "lesser gnu 3", "3", "29 June 2007"),
):
    HEADERS += [(_id, f"{_key} version", f"{_name} Version {_version}, {_date}"), (_id, _key, f"{_name} v{_version} {_version}")]
    HEADERS += [(_id, f"{_key} redistribute", form(what, _name, _version)) for form in (_gnu, _only) for what in ("This program", "This library")]
for _id in sorted({*WHOLE, *(h[0] for h in HEADERS)}):
    for _more in ("", " or later", " only") if "GPL" in _id else ("",):
        HEADERS.append((_id, "spdx " + _id.lower().replace("-", " ").replace(".", " "), f"SPDX-License-Identifier: {_id}{_more}"))


def forms() -> list[tuple[str, list[str], str]]:
    whole = [(name, key, (TEXTS / f"{name}.txt").read_text()) for name, key in WHOLE.items()]
    return [(name, key.split(), text) for name, key, text in HEADERS + whole]
