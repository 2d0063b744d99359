"""Public wordings of licence notices by family, and texts that only look like them.

A notice is mostly a lead, a name and a tail (``Released under`` ``the MIT License``
``, see LICENSE``); the classifier trains on their combinations and on sentences of
the licences themselves.
"""

#: How notices begin, in four languages.
LEADS = (
    "licensed under", "released under", "distributed under", "published under", "available under", "made available under", "provided under", "covered by", "governed by", "subject to",
    "under the terms of", "in accordance with", "this project is licensed under", "this work is licensed under", "this software is released under", "the code is under", "this file is part of a program under",
    "all content is licensed under", "you may use this file under", "redistribution is allowed under", "license:", "licence:", "spdx-license-identifier:", "this library is free software under", "open source under",
    "veröffentlicht unter", "lizenziert unter", "dieses projekt steht unter", "verfügbar unter", "nutzung gemäß", "sous licence", "distribué sous", "publié sous", "ce projet est sous", "mis à disposition selon",
    "publicado bajo", "distribuido bajo", "este proyecto está bajo", "con licencia", "",
)
MIDDLES = ("the", "the terms of the", "the terms and conditions of the", "a", "an", "version of the", "der", "die bedingungen der", "den bedingungen der", "la", "les termes de la", "la licencia", "los términos de la", "")
TAILS = (
    "", "see LICENSE", "see LICENSE.txt", "see the LICENSE file for details", "see the file COPYING", "for more information see the license text", "a copy of which is included", "only", "or later", "or any later version",
    "at your option", "unless stated otherwise", "please read it before use", "which can be found in the root directory", "siehe LICENSE", "voir le fichier LICENSE", "consulte el archivo LICENSE", "2020 the authors", "copyright 2019 by its contributors",
)
#: What each family is called.
NAMES: dict[str, tuple[str, ...]] = {
    "apache": ("Apache License", "Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 license", "Apache 2 licence", "Apache 2", "Apache-2.0", "Apache Software License", "Apache-Lizenz 2.0", "licence Apache 2.0", "licencia Apache 2.0", "ASL 2.0", "Apache Public License v2"),
    "mit": ("MIT License", "MIT licence", "MIT", "MIT/X11 license", "X11 license", "Expat license", "MIT-Lizenz", "licence MIT", "licencia MIT", "MIT open source license", "MIT-style license"),
    "bsd": ("BSD License", "BSD licence", "3-Clause BSD License", "2-clause BSD license", "BSD-3-Clause", "BSD-2-Clause", "New BSD License", "simplified BSD license", "modified BSD licence", "BSD-style license", "BSD-Lizenz", "licence BSD", "licencia BSD", "FreeBSD license"),
    "gpl": (
        "GNU General Public License", "GNU General Public License, version 3", "GNU General Public License v2.0", "GNU GPL", "GNU GPL version 2", "GPL", "GPLv2", "GPLv3", "GPL-2.0", "GPL-3.0-or-later", "GPL version 3", "GPL v2", "General Public License",
        "GNU Lesser General Public License", "GNU Lesser General Public License, version 2.1", "GNU LGPL", "GNU LGPL version 3", "LGPL", "LGPLv2.1", "LGPLv3", "LGPL-3.0", "GNU Affero General Public License", "GNU AGPL", "AGPL", "AGPLv3", "AGPL-3.0-only", "licence publique générale GNU", "licencia pública general de GNU", "GNU-GPL-Lizenz",
    ),
    "mpl": ("Mozilla Public License", "Mozilla Public License, version 2.0", "Mozilla Public License 1.1", "MPL", "MPL 2.0", "MPL-2.0", "MPLv2", "licence publique Mozilla", "licencia pública de Mozilla"),
    "creative_commons": (
        "Creative Commons Attribution 4.0 International License", "Creative Commons Attribution-ShareAlike 3.0", "Creative Commons Attribution-NonCommercial 4.0", "Creative Commons Attribution-NoDerivatives license", "Creative Commons license", "Creative Commons", "CC BY 4.0", "CC BY-SA 4.0", "CC BY-NC 4.0", "CC BY-NC-SA 3.0", "CC BY-ND 4.0", "CC-BY-4.0",
        "CC-BY-SA-3.0", "licence Creative Commons", "licencia Creative Commons", "Creative-Commons-Lizenz",
    ),
    "public_domain": ("public domain", "CC0", "CC0 1.0 Universal", "CC0-1.0", "Unlicense", "public domain dedication", "domaine public", "dominio público", "Gemeinfreiheit"),
    "proprietary": ("proprietary license", "commercial license", "end user license agreement", "all rights reserved", "tous droits réservés", "todos los derechos reservados", "alle Rechte vorbehalten"),
}
#: Sentences of the licences and their standard notices.
SENTENCES: dict[str, tuple[str, ...]] = {
    "apache": (
        "you may not use this file except in compliance with the License.",
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0",
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.',
        "See the License for the specific language governing permissions and limitations under the License.",
        "each Contributor hereby grants to You a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable copyright license to reproduce, prepare Derivative Works of, publicly display, publicly perform, sublicense, and distribute the Work",
    ),
    "mit": (
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software.',
        "and to permit persons to whom the Software is furnished to do so, subject to the following conditions",
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
        "in no event shall the authors or copyright holders be liable for any claim, damages or other liability, whether in an action of contract, tort or otherwise, arising from, out of or in connection with the software",
    ),
    "bsd": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
        "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
    ),
    "gpl": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
        "You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
        "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
        "The licenses for most software are designed to take away your freedom to share and change it.",
    ),
    "mpl": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
        "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
        "Covered Software is provided under this License on an as is basis, without warranty of any kind",
    ),
    "creative_commons": (
        "To view a copy of this license, visit https://creativecommons.org/licenses/by/4.0/",
        "You are free to share, copy and redistribute the material in any medium or format, and to adapt, remix, transform and build upon the material",
        "You must give appropriate credit, provide a link to the license, and indicate if changes were made.",
        "If you remix, transform, or build upon the material, you must distribute your contributions under the same license as the original.",
        "or send a letter to Creative Commons, PO Box 1866, Mountain View, CA 94042, USA",
    ),
    "public_domain": (
        "This is free and unencumbered software released into the public domain.",
        "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
        "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
        "This work is in the public domain and free of known copyright restrictions.",
        "The author dedicates this work to the public domain and disclaims all copyright.",
    ),
    "proprietary": (
        "All rights reserved.",
        "Copyright (c) 2020 by the publisher, all rights reserved.",
        "This document contains confidential and proprietary information.",
        "Unauthorized copying of this file, via any medium, is strictly prohibited.",
        "No part of this publication may be reproduced, stored or transmitted in any form without the prior written permission of the publisher.",
        "This software may not be copied, modified or distributed without a written agreement with the owner.",
    ),
}
#: What must stand in a paragraph for its family to be confirmed, if it shares no sentence: the family's name (patterns over lower-case words).
IDENTIFIERS: dict[str, str] = {
    "apache": r"\bapache (?:software |public )?(?:licen|lizenz|v?2)|\b(?:licence|licencia|license) apache\b|\basl 2",
    "mit": r"\b(?:mit|x11|expat)(?: x11)?(?: style| type)?(?: open source)? (?:licen[cs]e|lizenz)|\b(?:licen[cs]e|licencia|licensed under|spdx license identifier|under|lizenz)(?: the)? mit\b",
    "bsd": r"\bbsd\b|\bfreebsd licen",
    "gpl": r"\b[al]?gpl(?:v?\d|\b)|\bgnu (?:\w+ )?general public|\bgeneral public licen|\bpublique générale gnu|\bpública general de gnu",
    "mpl": r"\bmpl(?:v?\d|\b)|\bmozilla public|\b(?:publique|pública de) mozilla",
    "creative_commons": r"\bcreative commons|\bcc by\b",
    "public_domain": r"\bpublic domain\b|\bcc0\b|\bunlicense\b|\bdomaine public\b|\bdominio público\b|\bgemeinfrei",
    "proprietary": r"\ball rights reserved|\btous droits réservés|\btodos los derechos reservados|\balle rechte vorbehalten|\bproprietary licen|\bcommercial licen|\bend user licen",
}
#: Licences of no family above; half of them train the unknown class, the others calibrate it.
UNFAMILIAR = (
    "Eclipse Public License", "European Union Public Licence", "Orchid Community Terms, edition 5", "Artistic License", "Common Development and Distribution License", "zlib license", "ISC license", "Boost Software License", "SIL Open Font License",
    "Open Database License", "Python Software Foundation License", "Microsoft Reciprocal License", "house rules of the reading club", "Academic Free License", "customer agreement of the vendor", "Server Side terms, edition 1", "Business Source License", "PostgreSQL License",
    "University of the North licence", "Fair Licence", "Etalab licence ouverte", "CeCILL", "Open Government Licence", "NASA Open Source Agreement",
)
#: Sentences that share words with notices without being one; blanks take each filler.
ORDINARY = (
    "She renewed her {} licence last week and paid the fee.", "The officer asked for a {} license and the insurance papers.", "His {} licence expired in May.", "Without a {} license nobody may fish in the lake.",
    "The {} helicopter landed near the village and the apache tribe lived there.", "He studied at MIT before he moved to the {} institute.", "The general public was invited to the {} concert in the park.", "The {} program will be released in the spring.",
    "A copy of the {} report was obtained from the office and distributed to members.", "Permission to enter the {} building is granted by the guard.", "The {} warranty covers parts and labour for two years from the date of purchase.", "Water rights were reserved for the {} farms along the river.",
    "Creative work is common among the {} students of the school.", "The source of the {} river is subject to the weather in the mountains.", "You may use the {} kitchen provided that it is left clean.", "This is a notice for all persons who park at the {} gate.",
    "The {} company published its terms and conditions in the newspaper.", "Domain names and public roads were discussed at the {} meeting.", "The {} software was sold without a version for the old machines.", "All members reserved a table in the {} restaurant.",
    "The town lost the {} public domain along the river.", "The mozilla and the {} lizard are not the same animal.", "Copies of the {} file are kept in the archive under the stairs.", "The {} authors were free to change the documentation.", "He has the right to remain and all conditions of the {} visa are met.",
)
FILLERS = ("driving", "fishing", "new", "old", "city", "green", "first", "small", "national", "marriage")
