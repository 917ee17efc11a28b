"""Public license notices as templates.

The markup is that of the public license list: what stands between ``<<beginOptional>>`` and ``<<endOptional>>`` may be missing, and
``<<var;match="...">>`` stands for words of the author's own, ``.{a,b}`` for a to b characters and ``.+`` for any number from one on."""

from __future__ import annotations

_ANY = '<<var;name="own";match=".{0,400}">>'
_HOLDER = '<<var;name="holder";match=".{1,200}">>'


def _maybe(text: str) -> str:
    return f"<<beginOptional>>{text}<<endOptional>>"


_COPYRIGHT = _maybe(f'Copyright {_maybe("(c)")} <<var;name="copyright";match=".{{0,300}}">> {_maybe("All rights reserved.")}')
_AS_IS = (
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. "
    f"IN NO EVENT SHALL <<var;name=\"who\";match=\".{{1,120}}\">> BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_GRANT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, "
    "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"
)
_NOTICE = f"The above copyright notice and this permission notice {_maybe('(including the next paragraph)')} shall be included in all copies or substantial portions of the Software."
_BSD_START = (
    f"{_COPYRIGHT} Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    f"{_maybe('1.')} Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    f"{_maybe('2.')} Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
)
_BSD_NAME = f"{_maybe('3.')} Neither the name of {_HOLDER} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_END = (
    f"THIS SOFTWARE IS PROVIDED BY {_HOLDER} \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. "
    f"IN NO EVENT SHALL {_HOLDER} BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; "
    "OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_GPL_HEAD = f"{_maybe('This program is')} free software: you can redistribute it and/or modify it under the terms of the GNU {{kind}} {_maybe('as published by the Free Software Foundation')}, either version {{version}} of the License, or {_maybe('(at your option)')} any later version."
_GPL_TAIL = (
    f"{_ANY} is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {{kind}} for more details."
)
_KINDS = {"gpl": "General Public License", "lgpl": "Lesser General Public License", "agpl": "Affero General Public License"}
_VERSIONS = [("gpl", "2"), ("gpl", "3"), ("lgpl", "2.1"), ("lgpl", "3"), ("agpl", "3")]


def _spdx(name: str, version: str) -> str:
    return f"spdx:{name}-{version if '.' in version else version + '.0'}"


#: Label and template.
TEMPLATES: list[tuple[str, str]] = [
    ("spdx:mit", f"{_maybe('{m}')} {_COPYRIGHT} {_GRANT} {_NOTICE} {_AS_IS}".replace("{m}", "The MIT License (MIT)")),
    ("spdx:mit", f"{_GRANT} {_NOTICE}"),
    ("spdx:mit", f"{_maybe(f'This {_ANY} is')} {_maybe('released')}{_maybe('licensed')}{_maybe('distributed')} under the {_maybe('terms of the')} MIT license"),
    ("spdx:bsd-2-clause", f"{_BSD_START} {_BSD_END}"),
    ("spdx:bsd-3-clause", f"{_BSD_START} {_BSD_NAME} {_BSD_END}"),
    ("spdx:bsd-3-clause", f"{_BSD_START} {_BSD_NAME}"),
    ("spdx:isc", f"{_COPYRIGHT} Permission to use, copy, modify, and{_maybe('/or')} distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. "
     f"THE SOFTWARE IS PROVIDED \"AS IS\" AND {_HOLDER} DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."),
    ("spdx:0bsd", f"{_COPYRIGHT} Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. THE SOFTWARE IS PROVIDED \"AS IS\" AND {_HOLDER} DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE"),
    ("spdx:zlib", f"{_COPYRIGHT} This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. "
     "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: "
     f"{_maybe('1.')} The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. "
     f"{_maybe('2.')} Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. {_maybe('3.')} This notice may not be removed or altered from any source distribution."),
    ("spdx:bsl-1.0", "Boost Software License - Version 1.0 - August 17th, 2003"),
    ("spdx:bsl-1.0", "Distributed under the Boost Software License, Version 1.0"),
    ("spdx:unlicense", f"This is free and unencumbered software released into the public domain. {_maybe('Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.')}"),
    ("spdx:apache-2.0", "Apache License Version 2.0, January 2004"),
    ("spdx:apache-2.0", f"Licensed under the Apache License, {_maybe('{c}')} Version 2.0 {_maybe('(the License)')} {_maybe('you may not use this file except in compliance with the License. You may obtain a copy of the License at')}".replace("{c}", "the")),
    ("spdx:apache-2.0", f"Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use {_ANY} except in compliance with the License. You may obtain a copy of the License at http{_maybe('s')}://www.apache.org/licenses/LICENSE-2.0 "
     "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("spdx:mpl-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("spdx:epl-2.0", f"This program and the accompanying materials are made available under the terms of the Eclipse Public License {_maybe('v.')}{_maybe('version')} 2.0"),
    ("spdx:wtfpl", "DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE"),
    ("spdx:cc0-1.0", f"{_maybe('{a}')} CC0 1.0 {_maybe('Universal')}".replace("{a}", "Creative Commons")),
    *((_spdx(k, v), _GPL_HEAD.replace("{kind}", _KINDS[k]).replace("{version}", v)) for k, v in _VERSIONS),
    *((_spdx(k, v), (_GPL_HEAD + " " + _GPL_TAIL).replace("{kind}", _KINDS[k]).replace("{version}", v)) for k, v in _VERSIONS),
    *((_spdx(k, v), f"{_maybe(f'This {_ANY} is')} licensed under the {_maybe('terms of the')} GNU {_KINDS[k]} {_maybe('as published by the Free Software Foundation')}, {_maybe('either')} version {v}") for k, v in _VERSIONS),
    *(
        ("spdx:" + "-".join(["cc-by", *kind.split(), v]), f"licensed under {_maybe('a')}{_maybe('the')} {_maybe('Creative Commons')} {name} {kind} {v} {_maybe('International')} {_maybe('License')}")
        for kind in ("", "nc", "sa", "nd", "nc sa", "nc nd")
        for v in ("1.0", "2.0", "2.5", "3.0", "4.0")
        for name in ("CC BY", "Attribution")
    ),
]
