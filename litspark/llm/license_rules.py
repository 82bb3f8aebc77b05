"""Known licence sentences and ordered licence rules (data only)."""

from __future__ import annotations

# Sentences of public licence texts and notices, as they are usually written.
SENTENCES: dict[str, str] = {
    "mit_name": "The MIT License",
    "mit_released": "Released under the MIT License.",
    "mit_licensed": "Licensed under the MIT License.",
    "mit_grant": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "mit_notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "mit_warranty": "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.",
    "apache_licensed": "Licensed under the Apache License, Version 2.0.",
    "apache_header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
    "apache_copy": "You may obtain a copy of the License at",
    "apache_unless": "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "apache_see": "See the License for the specific language governing permissions and limitations under the License.",
    "gpl3_work": "This work is licensed under the GNU General Public License, version 3.",
    "gpl_free": "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "gpl2_free": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "gpl_hope": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.",
    "gpl_received": "You should have received a copy of the GNU General Public License along with this program.",
    "lgpl_free": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    "bsd_grant": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "bsd_source": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "bsd_binary": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "bsd_names": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "isc_grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "mpl_form": "This Source Code Form is subject to the terms of the Mozilla Public License, v.",
    "ccbync4": "Licensed under CC BY-NC 4.0.",
    "ccbync4_long": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "ccby4": "Licensed under CC BY 4.0.",
    "ccby4_long": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "ccbysa4": "Licensed under CC BY-SA 4.0.",
    "ccbysa4_long": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "unlicense": "This is free and unencumbered software released into the public domain.",
    "apache_definition": "\"License\" shall mean the terms and conditions for use, reproduction, and distribution as defined by Sections 1 through 9 of this document.",
    "apache_grant": "Subject to the terms and conditions of this License, each Contributor hereby grants to You a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable copyright license to reproduce, prepare Derivative Works of, publicly display, publicly perform, sublicense, and distribute the Work and such Derivative Works in Source or Object form.",
    "gpl3_text": "The GNU General Public License is a free, copyleft license for software and other kinds of works.",
    "gpl2_text": "By contrast, the GNU General Public License is intended to guarantee your freedom to share and change free software--to make sure the software is free for all its users.",
    "gpl2_only": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License version 2 as published by the Free Software Foundation.",
    "agpl_text": "The GNU Affero General Public License is a free, copyleft license for software and other kinds of works, specifically designed to ensure cooperation with the community in the case of network server software.",
    "agpl_free": "you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl2_text": "By contrast, the GNU General Public Licenses are intended to guarantee your freedom to share and change free software--to make sure the software is free for all its users.",
    "lgpl3_text": "This version of the GNU Lesser General Public License incorporates the terms and conditions of version 3 of the GNU General Public License, supplemented by the additional permissions listed below.",
    "lgpl3_free": "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "bsd_author": "The name of the author may not be used to endorse or promote products derived from this software without specific prior written permission.",
    "bsd_warranty": "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.",
    "zero_bsd_grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.",
    "isc_warranty": "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.",
    "zlib_warranty": "This software is provided 'as-is', without any express or implied warranty.",
    "zlib_grant": "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "boost_grant": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:",
    "wtfpl_copies": "Everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed as long as the name is changed.",
    "epl2_terms": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
}

# A licence, and the identifiers that follow one another (others may stand between); the first rule that fits counts for its licence.
RULES: list[tuple[str, str, tuple[str, ...]]] = [
    ("mit-text", "MIT", ("mit_grant", "mit_notice", "mit_warranty")),
    ("mit-name", "MIT", ("mit_name",)),
    ("mit-released", "MIT", ("mit_released",)),
    ("mit-licensed", "MIT", ("mit_licensed",)),
    ("apache-header", "Apache-2.0", ("apache_header", "apache_copy", "apache_unless", "apache_see")),
    ("apache-short", "Apache-2.0", ("apache_header", "apache_copy")),
    ("apache-licensed", "Apache-2.0", ("apache_licensed",)),
    ("gpl3-notice", "GPL-3.0-or-later", ("gpl_free", "gpl_hope", "gpl_received")),
    ("gpl2-notice", "GPL-2.0-or-later", ("gpl2_free", "gpl_hope", "gpl_received")),
    ("gpl3-work", "GPL-3.0", ("gpl3_work",)),
    ("lgpl-notice", "LGPL-2.1-or-later", ("lgpl_free",)),
    ("bsd3-text", "BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_names")),
    ("bsd2-text", "BSD-2-Clause", ("bsd_grant", "bsd_source", "bsd_binary")),
    ("isc-text", "ISC", ("isc_grant",)),
    ("mpl-form", "MPL-2.0", ("mpl_form",)),
    ("ccbync-name", "CC-BY-NC-4.0", ("ccbync4",)),
    ("ccbync-long", "CC-BY-NC-4.0", ("ccbync4_long",)),
    ("ccby-name", "CC-BY-4.0", ("ccby4",)),
    ("ccby-long", "CC-BY-4.0", ("ccby4_long",)),
    ("ccbysa-name", "CC-BY-SA-4.0", ("ccbysa4",)),
    ("ccbysa-long", "CC-BY-SA-4.0", ("ccbysa4_long",)),
    ("unlicense", "Unlicense", ("unlicense",)),
    ("apache-text", "Apache-2.0", ("apache_definition", "apache_grant")),
    ("gpl3-text", "GPL-3.0", ("gpl3_text",)),
    ("gpl2-text", "GPL-2.0", ("gpl2_text",)),
    ("gpl2-only", "GPL-2.0", ("gpl2_only",)),
    ("agpl-notice", "AGPL-3.0-or-later", ("agpl_free",)),
    ("agpl-text", "AGPL-3.0", ("agpl_text",)),
    ("lgpl2-text", "LGPL-2.1", ("lgpl2_text",)),
    ("lgpl3-notice", "LGPL-3.0-or-later", ("lgpl3_free",)),
    ("lgpl3-text", "LGPL-3.0", ("lgpl3_text",)),
    ("bsd3-author", "BSD-3-Clause", ("bsd_grant", "bsd_source", "bsd_binary", "bsd_author")),
    ("zero-bsd-text", "0BSD", ("zero_bsd_grant",)),
    ("zlib-text", "Zlib", ("zlib_warranty", "zlib_grant")),
    ("boost-text", "BSL-1.0", ("boost_grant",)),
    ("wtfpl-text", "WTFPL", ("wtfpl_copies",)),
    ("epl2-notice", "EPL-2.0", ("epl2_terms",)),
]

#: A rule that needs more gives way where a rule of the same licence text already fits: (weaker, stronger).
COVERED: list[tuple[str, str]] = [("BSD-2-Clause", "BSD-3-Clause")]

# Licences by their public identifier, with the names that notices call them by.
NAMES: dict[str, tuple[str, ...]] = {
    "0BSD": ("BSD Zero Clause License",),
    "AGPL-3.0": ("GNU Affero General Public License v3.0", "GNU Affero General Public License, version 3", "AGPLv3 License"),
    "Apache-2.0": ("Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 License", "Apache-2.0 License"),
    "Artistic-2.0": ("Artistic License 2.0",),
    "BSD-2-Clause": ("BSD 2-Clause License", "Simplified BSD License"),
    "BSD-3-Clause": ("BSD 3-Clause License", "New BSD License"),
    "BSL-1.0": ("Boost Software License, Version 1.0", "Boost Software License 1.0"),
    "CC-BY-4.0": ("Creative Commons Attribution 4.0 International License",),
    "CC-BY-NC-4.0": ("Creative Commons Attribution-NonCommercial 4.0 International License",),
    "CC-BY-NC-ND-4.0": ("Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License",),
    "CC-BY-NC-SA-4.0": ("Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License",),
    "CC-BY-ND-4.0": ("Creative Commons Attribution-NoDerivatives 4.0 International License",),
    "CC-BY-SA-4.0": ("Creative Commons Attribution-ShareAlike 4.0 International License",),
    "CC0-1.0": ("CC0 1.0 Universal License",),
    "EPL-2.0": ("Eclipse Public License 2.0", "Eclipse Public License, Version 2.0"),
    "EUPL-1.2": ("European Union Public License 1.2",),
    "GPL-2.0": ("GNU General Public License v2.0", "GNU General Public License, version 2", "GPLv2 License"),
    "GPL-3.0": ("GNU General Public License v3.0", "GNU General Public License, version 3", "GPLv3 License"),
    "ISC": ("ISC License",),
    "LGPL-2.1": ("GNU Lesser General Public License v2.1", "GNU Lesser General Public License, version 2.1"),
    "LGPL-3.0": ("GNU Lesser General Public License v3.0", "GNU Lesser General Public License, version 3"),
    "MIT": ("MIT License", "MIT license terms"),
    "MPL-2.0": ("Mozilla Public License 2.0", "Mozilla Public License, version 2.0"),
    "Unlicense": ("Unlicense License", "Unlicense"),
    "WTFPL": ("WTFPL License",),
    "Zlib": ("zlib License",),
}
# How notices name a licence, and what announces a public identifier.
FORMS = (
    "Licensed under the {}.", "Released under the {}.", "Distributed under the {}.", "Available under the {}.", "This project is licensed under the {}.", "This project is released under the {}.",
    "This project is licensed under the {} - see the LICENSE file for details.", "This project is licensed under the terms of the {}.", "This software is licensed under the {}.", "This software is released under the {}.",
    "This work is licensed under the {}.", "This work is licensed under a {}.", "This code is licensed under the {}.", "This file is licensed under the {}.", "This library is licensed under the {}.",
)
ANNOUNCED = "SPDX-License-Identifier"


def _plain(name: str) -> str:
    return "".join(c if c.isalnum() else "_" for c in name.lower())


def named_sentences() -> dict[str, str]:
    """Sentence -> identifier for every licence, name and form; all that name one licence share an identifier."""
    return {form.format(name): f"named_{_plain(licence)}" for licence, names in NAMES.items() for name in names for form in FORMS}


def announced_sentences() -> dict[str, str]:
    """The announcement with a licence's public identifier behind it -> identifier."""
    return {f"{ANNOUNCED} {value}": f"spdx_{_plain(licence)}" for licence in NAMES for value in (licence, f"{licence}-only", f"{licence}-or-later")}


RULES += [(f"{_plain(licence)}-named", licence, (f"named_{_plain(licence)}",)) for licence in NAMES]
RULES += [(f"{_plain(licence)}-spdx", licence, (f"spdx_{_plain(licence)}",)) for licence in NAMES]
