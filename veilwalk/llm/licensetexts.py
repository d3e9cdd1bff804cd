"""Notices, headers and texts of public licences, in the order of their names.

A licence has one entry for each form in which it is met: the sentence that names it, the block at the top of a source
file, and its own text (of long licences the opening, up to the first definitions). Names are those of the SPDX list in
lower case; lines of SPDX identifiers are made by rule from the names.
"""

from __future__ import annotations

_GPL_HEADER = (
    "This {work} is free software: you can redistribute it and/or modify it under the terms of the GNU {kind}General Public License as published by "
    "the Free Software Foundation, either version {version} of the License, or (at your option) any later version. This {work} is distributed in the "
    "hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. "
    "See the GNU {kind}General Public License for more details. You should have received a copy of the GNU {kind}General Public License along with "
    "this {work}. If not, see <https://www.gnu.org/licenses/>."
)
_GPL_OPENING = (
    "GNU {kind}GENERAL PUBLIC LICENSE Version {version}, {date} Copyright (C) Free Software Foundation, Inc. Everyone is permitted to copy and "
    "distribute verbatim copies of this license document, but changing it is not allowed. {rest}"
)
_BSD_TWO = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution."
)
_BSD_THIRD = (
    " 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this "
    "software without specific prior written permission."
)
_BSD_END = (
    ' THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED '
    "TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
    "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
    "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF "
    "LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, "
    "EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_MIT_GRANT = (
    'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), '
    "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, "
    "and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: "
    "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."
)
_MIT_END = (
    ' THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, "
    "DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE "
    "USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_GPL2_REST = (
    "Preamble The licenses for most software are designed to take away your freedom to share and change it. By contrast, the GNU General Public License "
    "is intended to guarantee your freedom to share and change free software--to make sure the software is free for all its users."
)
_GPL3_REST = (
    "Preamble The GNU General Public License is a free, copyleft license for software and other kinds of works. The licenses for most software and "
    "other practical works are designed to take away your freedom to share and change the works."
)
_AGPL_REST = (
    "Preamble The GNU Affero General Public License is a free, copyleft license for software and other kinds of works, specifically designed to ensure "
    "cooperation with the community in the case of network server software."
)
_LGPL21_REST = (
    "[This is the first released version of the Lesser GPL. It also counts as the successor of the GNU Library Public License, version 2, hence the "
    "version number 2.1.] Preamble The licenses for most software are designed to take away your freedom to share and change it."
)
_LGPL3_REST = (
    "This version of the GNU Lesser General Public License incorporates the terms and conditions of version 3 of the GNU General Public License, "
    "supplemented by the additional permissions listed below."
)

TEMPLATES: dict[str, list[str]] = {
    "agpl-3.0": [
        "This program is licensed under the GNU Affero General Public License, version 3.",
        _GPL_HEADER.format(work="program", kind="Affero ", version="3"),
        _GPL_OPENING.format(kind="AFFERO ", version="3", date="19 November 2007", rest=_AGPL_REST),
        _GPL_OPENING.format(kind="AFFERO ", version="3", date="19 November 2007", rest=""),
    ],
    "apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a '
        "copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed "
        'under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for '
        "the specific language governing permissions and limitations under the License.",
        "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/",
        "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION "
        '1. Definitions. "License" shall mean the terms and conditions for use, reproduction, and distribution as defined by Sections 1 through 9 of this '
        'document. "Licensor" shall mean the copyright owner or entity authorized by the copyright owner that is granting the License.',
    ],
    "bsd-2-clause": ["Released under the BSD 2-Clause License.", "BSD 2-Clause License " + _BSD_TWO, _BSD_TWO, _BSD_TWO + _BSD_END],
    "bsd-3-clause": ["Released under the BSD 3-Clause License.", "BSD 3-Clause License " + _BSD_TWO + _BSD_THIRD, _BSD_TWO + _BSD_THIRD, _BSD_TWO + _BSD_THIRD + _BSD_END],
    "bsl-1.0": [
        "Distributed under the Boost Software License, Version 1.0.",
        "Boost Software License - Version 1.0 - August 17th, 2003 Permission is hereby granted, free of charge, to any person or organization obtaining a "
        'copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and '
        "transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so.",
    ],
    "cc-by-4.0": [
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License. https://creativecommons.org/licenses/by/4.0/",
    ],
    "cc-by-nc-4.0": [
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License. https://creativecommons.org/licenses/by-nc/4.0/",
    ],
    "cc-by-sa-4.0": [
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License. https://creativecommons.org/licenses/by-sa/4.0/",
    ],
    "cc0-1.0": [
        "Dedicated to the public domain under CC0 1.0.",
        "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work. CC0 1.0 Universal "
        "https://creativecommons.org/publicdomain/zero/1.0/",
    ],
    "gpl-2.0": [
        "This work is licensed under the GNU General Public License, version 2.",
        _GPL_HEADER.format(work="program", kind="", version="2"),
        _GPL_OPENING.format(kind="", version="2", date="June 1991", rest=_GPL2_REST),
        _GPL_OPENING.format(kind="", version="2", date="June 1991", rest=""),
        "GNU GENERAL PUBLIC LICENSE Version 2, June 1991",
    ],
    "gpl-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        _GPL_HEADER.format(work="program", kind="", version="3"),
        _GPL_OPENING.format(kind="", version="3", date="29 June 2007", rest=_GPL3_REST),
        _GPL_OPENING.format(kind="", version="3", date="29 June 2007", rest=""),
        "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007",
    ],
    "isc": [
        "Released under the ISC License.",
        "ISC License Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that "
        'the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL '
        "WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.",
    ],
    "lgpl-2.1": [
        "This library is licensed under the GNU Lesser General Public License, version 2.1.",
        _GPL_HEADER.format(work="library", kind="Lesser ", version="2.1"),
        _GPL_OPENING.format(kind="LESSER ", version="2.1", date="February 1999", rest=_LGPL21_REST),
        _GPL_OPENING.format(kind="LESSER ", version="2.1", date="February 1999", rest=""),
    ],
    "lgpl-3.0": [
        "This library is licensed under the GNU Lesser General Public License, version 3.",
        _GPL_HEADER.format(work="library", kind="Lesser ", version="3"),
        _GPL_OPENING.format(kind="LESSER ", version="3", date="29 June 2007", rest=_LGPL3_REST),
        _GPL_OPENING.format(kind="LESSER ", version="3", date="29 June 2007", rest=""),
    ],
    "mit": ["Released under the MIT License.", "MIT License", "MIT License " + _MIT_GRANT, "MIT License " + _MIT_GRANT + _MIT_END],
    "mpl-2.0": [
        "Licensed under the Mozilla Public License, Version 2.0.",
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You "
        "can obtain one at https://mozilla.org/MPL/2.0/.",
        'Mozilla Public License Version 2.0 1. Definitions 1.1. "Contributor" means each individual or legal entity that creates, contributes to the '
        "creation of, or owns Covered Software.",
    ],
    "proprietary": ["All rights reserved."],
    "unlicense": [
        "This is free and unencumbered software released into the public domain under the Unlicense.",
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute "
        "this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    ],
    "zlib": [
        "Distributed under the zlib License.",
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising "
        "from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to "
        "alter it and redistribute it freely, subject to the following restrictions.",
    ],
}

#: A notice or licence text holds one of these in lower case, with a capital or in capitals.
CUES = (
    "icens", "ICENS", "opyright", "OPYRIGHT", "ights reserved", "IGHTS RESERVED", "ublic domain", "UBLIC DOMAIN", "CC0", "CC BY", "CC-BY", "SPDX",
    "ermission", "ERMISSION", "edistribut", "EDISTRIBUT", "arrant", "ARRANT", "AS IS", "free software", "unencumbered",
)
