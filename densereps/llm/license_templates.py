"""Licence texts as templates, in several usual wordings; fixed public texts.

MIT, ISC and the BSD licences are given whole, and by their openings where those tell the licence. Apache, GPL, LGPL,
AGPL and MPL are given by the standard notices for files, Creative Commons by short notices; their whole texts are not.
"""

MIT_BODY = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
    'documentation files (the "Software"), to deal in the Software without restriction, including without limitation the '
    "rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit "
    "persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and "
    "this permission notice shall be included in all copies or substantial portions of the Software."
)
APACHE_BODY = (
    'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the '
    "License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable "
    'law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES '
    "OR CONDITIONS OF ANY KIND, either express or implied."
)
GPL_BODY = (
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License "
    "as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."
)
GPL2_BODY = GPL_BODY.replace("version 3", "version 2")
LGPL_BODY = GPL_BODY.replace("GNU General", "GNU Lesser General")
AGPL_BODY = GPL_BODY.replace("GNU General", "GNU Affero General")
MPL_BODY = (
    "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not "
    "distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."
)
MIT_WHOLE = MIT_BODY + (
    ' THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE '
    "WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR "
    "COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, "
    "ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_BSD_OPENING = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following "
    "conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the "
    "following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and "
    "the following disclaimer in the documentation and/or other materials provided with the distribution."
)
_BSD_NAMES = (
    " 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products "
    "derived from this software without specific prior written permission."
)
_BSD_DISCLAIMER = (
    ' THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, '
    "BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT "
    "SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL "
    "DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS "
    "INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING "
    "NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
BSD2_WHOLE, BSD3_WHOLE = _BSD_OPENING + _BSD_DISCLAIMER, _BSD_OPENING + _BSD_NAMES + _BSD_DISCLAIMER
_ISC_DISCLAIMER = (
    ' THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED '
    "WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR "
    "CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, "
    "NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
ISC_BODY = (
    "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, "
    "provided that the above copyright notice and this permission notice appear in all copies."
)
ISC_WHOLE = ISC_BODY + _ISC_DISCLAIMER

#: Short notices: with each of these openings, the licence by each of its names.
OPENINGS = ("Licensed under {}.", "Released under {}.", "This work is licensed under {}.", "Distributed under {}.")
NAMES = {
    "MIT": ["the MIT License"],
    "Apache-2.0": ["the Apache License, Version 2.0"],
    "BSD-3-Clause": ["the 3-Clause BSD License"],
    "BSD-2-Clause": ["the 2-Clause BSD License"],
    "ISC": ["the ISC License"],
    "MPL-2.0": ["the Mozilla Public License, Version 2.0"],
    "GPL-2.0": ["the GNU General Public License, version 2"],
    "GPL-3.0": ["the GNU General Public License, version 3"],
    "LGPL-3.0": ["the GNU Lesser General Public License, version 3"],
    "AGPL-3.0": ["the GNU Affero General Public License, version 3"],
    "CC-BY-4.0": ["CC BY 4.0", "a Creative Commons Attribution 4.0 International License"],
    "CC-BY-SA-4.0": ["CC BY-SA 4.0", "a Creative Commons Attribution-ShareAlike 4.0 International License"],
    "CC-BY-NC-4.0": ["CC BY-NC 4.0", "a Creative Commons Attribution-NonCommercial 4.0 International License"],
    "CC0-1.0": ["CC0 1.0"],
}
BODIES = {
    "MIT": [MIT_BODY, MIT_WHOLE],
    "Apache-2.0": [APACHE_BODY],
    "GPL-2.0": [GPL2_BODY],
    "GPL-3.0": [GPL_BODY],
    "LGPL-3.0": [LGPL_BODY],
    "AGPL-3.0": [AGPL_BODY],
    "MPL-2.0": [MPL_BODY],
    "BSD-2-Clause": [BSD2_WHOLE],
    "BSD-3-Clause": [BSD3_WHOLE],
    "ISC": [ISC_BODY, ISC_WHOLE],
}


#: Tags of files: with this opening, the licence by its identifier. Those of GPL kinds may go on with "-only" or "-or-later".
TAG = "SPDX-License-Identifier: {}"
SUFFIXED = ("GPL-2.0", "GPL-3.0", "LGPL-3.0", "AGPL-3.0")


def templates() -> list[tuple[str, str]]:
    """(licence, text) of every template."""
    short = [(k, opening.format(name)) for k, names in NAMES.items() for name in names for opening in OPENINGS]
    short += [(k, TAG.format(k)) for k in NAMES] + [(k, TAG.format(f"{k}-{end}")) for k in SUFFIXED for end in ("only", "or-later")]
    return short + [(k, text) for k, texts in BODIES.items() for text in texts]
