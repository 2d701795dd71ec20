"""Signatures of license texts, file headers and notices, written by hand on normalised text (lower-case words with single blanks).

Each is (label, regular expression); `literal` gives the longest run of words that every match of it holds, its keyword.
"""

from __future__ import annotations

import re

#: Passages of the licenses themselves: priority 4.
BODIES: tuple[tuple[str, str], ...] = (
    # permissive grants
    ("mit", r"permission is hereby granted free of charge to any person obtaining a copy of (?:this|the) software and associated documentation"),
    ("mit", r"the above copyright notice and this permission notice(?: including the next paragraph)? shall be included in all copies or substantial portions of the software"),
    ("mit", r"to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies"),
    ("mit", r"in no event shall the authors or copyright holders be liable for any claim damages or other liability"),
    ("x11", r"except as contained in this notice the names? of(?: \S+){1,8}? shall not be used in advertising or otherwise to promote the sale use or other dealings"),
    ("mit-advertising", r"permission is hereby granted without written agreement and without license or royalty fees to use copy modify and distribute this software"),
    ("json", r"the software shall be used for good not evil"),
    ("ncsa", r"to deal with the software without restriction including without limitation the rights to use copy modify merge publish distribute"),
    ("isc", r"permission to use copy modify and(?: or)? distribute this software for any purpose with or without fee is hereby granted"),
    ("isc", r"the software is provided as is and(?: \S+){1,6}? disclaims all warranties with regard to this software"),
    ("hpnd", r"permission to use copy modify(?: and)? distribute(?: and sell)? this software and its documentation for any purpose is hereby granted without fee"),
    ("hpnd", r"not be used in advertising or publicity pertaining to distribution of the software without specific written prior permission"),
    ("hpnd", r"makes no representations about the suitability of this software for any purpose it is provided as is without express or implied warranty"),
    ("postgresql", r"permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement is hereby granted"),
    ("bsl-1.0", r"permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license"),
    ("bsl-1.0", r"unless such copies or derivative works are solely in the form of machine executable object code generated by a source language processor"),
    ("upl-1.0", r"subject to the condition set forth below permission is hereby granted to any person obtaining a copy of this software associated documentation and or data"),
    ("unicode", r"permission is hereby granted free of charge to any person obtaining a copy of (?:the )?(?:unicode )?data files and any associated documentation"),
    ("blueoak", r"this license gives everyone as much permission to work with this software as possible while protecting contributors from liability"),
    ("fair", r"usage of the works is permitted provided that this instrument is retained with the works so that any entity that uses the works is notified of this instrument"),
    ("beerware", r"as long as you retain this notice you can do whatever you want with this stuff"),
    ("beerware", r"if we meet some day and you think this stuff is worth it you can buy me a beer in return"),
    ("wtfpl", r"everyone is permitted to copy and distribute verbatim or modified copies of this license document and changing it is allowed as long as the name is changed"),
    ("wtfpl", r"you just do what the fuck you want to"),
    # redistribution clauses
    ("bsd", r"redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"),
    ("bsd", r"redistributions of source code must retain the (?:above )?copyright notices? this list of conditions and the following disclaimers?"),
    ("bsd", r"redistributions in binary form must reproduce the (?:above )?copyright notices? this list of conditions and the following disclaimers?"),
    ("bsd-3-clause", r"neither the names? of(?: \S+){1,10}? nor the names of (?:its|their|any|other) contributors may be used to endorse or promote products"),
    ("bsd-3-clause", r"may not be used to endorse or promote products derived from this software without specific prior written permission"),
    ("bsd-4-clause", r"all advertising materials mentioning features or use of this software must display the following acknowledge?ment"),
    ("bsd", r"this software is provided by(?: the)?(?: \S+){1,8}? as is and any express or implied warranties including but not limited to the implied warranties"),
    ("bsd", r"loss of use data or profits or business interruption however caused and on any theory of liability whether in contract strict liability or tort"),
    ("freebsd", r"the views and conclusions contained in the software and documentation are those of the authors and should not be interpreted as representing official policies"),
    ("bsd-3-clause-clear", r"no express or implied licenses to any party s patent rights are granted by this license"),
    ("bsd-plus-patent", r"such license shall not apply to any other combinations which include the contribution no hardware per se is licensed"),
    ("sleepycat", r"redistributions in any form must be accompanied by information on how to obtain complete source code"),
    ("openssl", r"this product includes software developed by the openssl project for use in the openssl toolkit"),
    ("ssleay", r"this product includes cryptographic software written by eric young"),
    ("bsd-4-clause", r"this product includes software developed by the university of california"),
    ("apache-1.1", r"this product includes software developed by the apache (?:software foundation|group)"),
    ("apache-1.1", r"products derived from this software may not be called apache nor may apache appear in their name"),
    ("php", r"products derived from this software may not be called php nor may php appear in their name"),
    ("zope", r"names of the copyright holders must not be used to endorse or promote products derived from this software without prior written permission"),
    ("intel", r"the name of intel corporation may not be used to endorse or promote products"),
    # permissive with patents
    ("apache-2.0", r"grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable copyright license to reproduce prepare derivative works of"),
    ("apache-2.0", r"grants to you a perpetual worldwide non exclusive no charge royalty free irrevocable except as stated in this section patent license"),
    ("apache-2.0", r"you must give any other recipients of the work or derivative works a copy of this license"),
    ("apache-2.0", r"you must cause any modified files to carry prominent notices stating that you changed the files"),
    ("apache-2.0", r"unless you explicitly state otherwise any contribution intentionally submitted for inclusion in the work by you to the licensor"),
    ("ms-pl", r"each contributor grants you a non exclusive worldwide royalty free license under its licensed patents to make have made use sell offer for sale import"),
    ("ms-pl", r"this license governs use of the accompanying software if you use the software you accept this license"),
    ("mulanpsl-2.0", r"each contributor hereby grants to you a perpetual worldwide royalty free non exclusive irrevocable copyright license to reproduce use modify or distribute its contribution"),
    ("afl-3.0", r"licensor grants you a worldwide royalty free non exclusive sublicensable license for the duration of the copyright"),
    ("osl-3.0", r"external deployment means the use distribution or communication of the original work or derivative works in any way"),
    # copyleft
    ("gpl-2.0", r"the licenses for most software are designed to take away your freedom to share and change it"),
    ("gpl-2.0", r"you may modify your copy or copies of the program or any portion of it thus forming a work based on the program"),
    ("gpl-2.0", r"each time you redistribute the program or any work based on the program the recipient automatically receives a license"),
    ("gpl-3.0", r"the gnu general public license is a free copyleft license for software and other kinds of works"),
    ("gpl-3.0", r"the licenses for most software and other practical works are designed to take away your freedom to share and change the works"),
    ("gpl-3.0", r"you may convey verbatim copies of the program s source code as you receive it in any medium"),
    ("gpl-3.0", r"this license will therefore apply along with any applicable section 7 additional terms to the whole of the work and all its parts"),
    ("gpl", r"everyone is permitted to copy and distribute verbatim copies of this license document but changing it is not allowed"),
    ("gpl", r"when we speak of free software we are referring to freedom not price"),
    ("agpl-3.0", r"your modified version must prominently offer all users interacting with it remotely through a computer network"),
    ("agpl-3.0", r"the gnu affero general public license is a free copyleft license for software and other kinds of works specifically designed to ensure cooperation"),
    ("lgpl-2.1", r"this license the lesser general public license applies to some specially designated software packages"),
    ("lgpl-2.0", r"this license the library general public license applies to some specially designated free software foundation software"),
    ("lgpl-3.0", r"this version of the gnu lesser general public license incorporates the terms and conditions of version 3 of the gnu general public license"),
    ("lgpl", r"a program that contains no derivative of any portion of the library but is designed to work with the library by being compiled or linked with it"),
    ("gfdl", r"the purpose of this license is to make a manual textbook or other functional and useful document free in the sense of freedom"),
    ("gpl-classpath", r"linking this library statically or dynamically with other modules is making a combined work based on this library"),
    ("gpl-classpath", r"gives? you permission to link this library with independent modules to produce an executable regardless of the license terms"),
    ("gpl-exception", r"as a special exception(?: to the \S+)?(?: \S+){0,12}? give you (?:unlimited )?permission to (?:link|copy|combine|compile|distribute)"),
    ("mpl-2.0", r"covered software is provided under this license on an as is basis without warranty of any kind"),
    ("mpl-2.0", r"all distribution of covered software in source code form including any modifications that you create or to which you contribute must be under the terms of this license"),
    ("mpl-1.1", r"the initial developer hereby grants you a world wide royalty free non exclusive license subject to third party intellectual property claims"),
    ("epl", r"the accompanying program is provided under the terms of this eclipse public license"),
    ("epl", r"any use reproduction or distribution of the program constitutes recipient s acceptance of this agreement"),
    ("cpl-1.0", r"the accompanying program is provided under the terms of this common public license"),
    ("ipl-1.0", r"the accompanying program is provided under the terms of this ibm public license"),
    ("cddl", r"any covered software that you distribute or otherwise make available in executable form must also be made available in source code form"),
    ("eupl", r"the licensor hereby grants you a worldwide royalty free non exclusive sub ?licen[sc]able licen[sc]e to do the following for the duration of copyright vested in the original work"),
    ("cecill", r"this agreement is a free software license agreement that is the result of discussions between its authors"),
    ("artistic-1.0", r"the intent of this document is to state the conditions under which a package may be copied such that the copyright holder maintains some semblance of artistic control"),
    ("artistic-2.0", r"this license establishes the terms under which a given free software package may be copied modified distributed and or redistributed"),
    ("ms-rl", r"for any file you distribute that contains code from the software in source code or binary format you must provide recipients the source code to that file"),
    ("qpl", r"you may distribute your modifications in a form that is separate from the software such as patches"),
    ("lppl", r"you may distribute a complete unmodified copy of the work as you received it distribution of only part of the work is considered modification of the work"),
    ("vim", r"there are no restrictions on distributing unmodified copies of vim except that they must include this license text"),
    ("ruby", r"you may make and give away verbatim copies of the source form of the software without restriction provided that you duplicate all of the original copyright notices"),
    ("sspl", r"if you make the functionality of the program or a modified version available to third parties as a service you must make the service source code available"),
    # attribution-only
    ("zlib", r"this software is provided as is without any express or implied warranty in no event will the authors be held liable for any damages arising from the use of this software"),
    ("zlib", r"permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely"),
    ("zlib", r"the origin of this software must not be misrepresented you must not claim that you wrote the original software"),
    ("zlib", r"altered source versions must be plainly marked as such and must not be misrepresented as being the original software"),
    ("libpng", r"the png reference library is supplied as is"),
    ("ijg", r"this software is based in part on the work of the independent jpeg group"),
    ("freetype", r"portions of this software are copyright(?: \S+){0,6}? the freetype project"),
    ("python-2.0", r"psf hereby grants licensee a nonexclusive royalty free world wide license to reproduce analyze test perform and or display publicly"),
    ("python-2.0", r"this license agreement is between the python software foundation psf and the individual or organization licensee"),
    ("w3c", r"by obtaining using and or copying this work you the licensee agree that you have read understood and will comply with the following terms"),
    ("ofl-1.1", r"the font software may be modified altered or added to and in particular the designs of glyphs or characters in the fonts may be modified"),
    ("ofl-1.1", r"the goals of the open font license ofl are to stimulate worldwide development of collaborative font projects"),
    ("info-zip", r"redistributions of source code in whole or in part must retain the above copyright notice definition disclaimer and this list of conditions"),
    # dedications
    ("unlicense", r"this is free and unencumbered software released into the public domain"),
    ("unlicense", r"anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary"),
    ("cc0", r"has waived all copyright and related or neighboring rights to"),
    ("cc0", r"has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law"),
    ("cc0", r"affirmer hereby overtly fully permanently irrevocably and unconditionally waives abandons and surrenders all of affirmer s copyright"),
    ("pddl", r"the rightsholder dedicates to the public domain all copyright and related rights"),
    # culture and data
    ("cc", r"you are free to share copy and redistribute the material in any medium or format"),
    ("cc-by", r"you must give appropriate credit provide a link to the license and indicate if changes were made"),
    ("cc-by-nc", r"you may not use the material for commercial purposes"),
    ("cc-by-sa", r"if you remix transform or build upon the material you must distribute your contributions under the same license as the original"),
    ("cc-by-nd", r"if you remix transform or build upon the material you may not distribute the modified material"),
    ("cc", r"by exercising the licensed rights defined below you accept and agree to be bound by the terms and conditions of this creative commons"),
    ("odbl", r"you are free to share to copy distribute and use the database to create to produce works from the database"),
    ("odbl", r"if you publicly use any adapted version of this database or works produced from an adapted database you must also offer that adapted database under the odbl"),
    # use-restricted
    ("busl-1.1", r"the licensor hereby grants you the right to copy modify create derivative works redistribute and make non production use of the licensed work"),
    ("elastic-2.0", r"you may not provide the software to third parties as a hosted or managed service"),
    ("commons-clause", r"the license does not grant to you(?: and you are not granted)? the right to sell the software"),
    ("polyform", r"the licensor grants you a copyright license for the software to do everything you might do with the software that would otherwise infringe"),
    ("openrail", r"you agree not to use the model or derivatives of the model in any way that violates any applicable national federal state local or international law"),
    ("openrail", r"use based restrictions as referenced in"),
    ("llama", r"you are granted a non exclusive worldwide non transferable and royalty free limited license under meta s intellectual property"),
    ("hippocratic", r"the software must not be used by any person or entity for any systems activities or other uses that violate any human rights laws"),
    ("eula", r"by installing copying or otherwise using (?:the|this) software(?: product)? you agree to be bound by the terms of this"),
    ("eula", r"you may not reverse engineer decompile or disassemble the software"),
    ("eula", r"the software is licensed not sold"),
)

#: File headers, statements of a license and notices: priority 3.
NOTICES: tuple[tuple[str, str], ...] = (
    ("apache-2.0", r"licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license"),
    ("apache-2.0", r"you may obtain a copy of the license at https? www apache org licenses license 2 0"),
    ("apache-2.0", r"unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis"),
    ("apache-2.0", r"licensed to the apache software foundation asf under one or more contributor license agreements"),
    ("apache-2.0", r"see the notice file distributed with this work for additional information regarding copyright ownership"),
    ("apache-2.0", r"www apache org licenses license 2 0"),
    ("ecl-2.0", r"educational community license version 2 0"),
    ("gpl", r"is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("lgpl", r"is free software you can redistribute it and or modify it under the terms of the gnu (?:lesser|library) general public license"),
    ("agpl", r"is free software you can redistribute it and or modify it under the terms of the gnu affero general public license"),
    ("gpl-2.0", r"gnu general public license as published by the free software foundation (?:either )?version 2 of the license"),
    ("gpl-3.0", r"gnu general public license as published by the free software foundation (?:either )?version 3 of the license"),
    ("lgpl-2.0", r"gnu (?:lesser|library) general public license as published by the free software foundation (?:either )?version 2 of the license"),
    ("lgpl-2.1", r"gnu lesser general public license as published by the free software foundation (?:either )?version 2 1 of the license"),
    ("lgpl-3.0", r"gnu lesser general public license as published by the free software foundation (?:either )?version 3 of the license"),
    ("agpl-3.0", r"gnu affero general public license as published by the free software foundation (?:either )?version 3 of the license"),
    ("gpl", r"either version [23](?: 0)? of the license or at your option any later version"),
    ("gpl", r"without even the implied warranty of merchantability or fitness for a particular purpose see the gnu(?: \S+)? general public license for more details"),
    ("gpl", r"you should have received a copy of the gnu general public license along with"),
    ("lgpl", r"you should have received a copy of the gnu (?:lesser|library) general public license along with"),
    ("agpl", r"you should have received a copy of the gnu affero general public license along with"),
    ("gpl", r"www gnu org licenses gpl(?: [0-9] [0-9])?"),
    ("lgpl", r"www gnu org licenses lgpl(?: [0-9] [0-9])?"),
    ("agpl", r"www gnu org licenses agpl(?: [0-9] [0-9])?"),
    ("gfdl", r"permission is granted to copy distribute and or modify this document under the terms of the gnu free documentation license"),
    ("gfdl", r"with no invariant sections no front cover texts and no back cover texts"),
    ("gpl-exception", r"gcc runtime library exception"),
    ("mpl-2.0", r"this source code form is subject to the terms of the mozilla public license v 2 0"),
    ("mpl-2.0", r"if a copy of the mpl was not distributed with this file you can obtain one at"),
    ("mpl-2.0", r"this source code form is incompatible with secondary licenses"),
    ("mpl-1.1", r"the contents of this file are subject to the mozilla public license version 1 1"),
    ("mpl-1.1", r"software distributed under the license is distributed on an as is basis without warranty of any kind either express or implied see the license for the specific language governing rights"),
    ("mpl", r"(?:https?|www) (?:www )?mozilla org mpl"),
    ("npl", r"the contents of this file are subject to the netscape public license"),
    ("epl-1.0", r"made available under the terms of the eclipse public license v(?:ersion)? 1 0"),
    ("epl-2.0", r"made available under the terms of the eclipse public license v(?:ersion)? ?2 0"),
    ("edl", r"available under the terms of the eclipse distribution license v(?:ersion)? 1 0"),
    ("cddl", r"the contents of this file are subject to the terms of the common development and distribution license"),
    ("cddl", r"you can obtain a copy of the license at(?: \S+){1,8}? opensolaris license"),
    ("osl-3.0", r"licensed under the open software license version 3 0"),
    ("afl-3.0", r"licensed under the academic free license version (?:3 0|2 1)"),
    ("eupl", r"licensed under the eupl"),
    ("eupl", r"you may not use this work except in compliance with the licen[sc]e"),
    ("cecill", r"this software is governed by the cecill(?: [bc])? license under french law"),
    ("perl", r"you may distribute under the terms of either the gnu general public license or the artistic license"),
    ("perl", r"you can redistribute it and or modify it under the same terms as perl itself"),
    ("ruby", r"you can redistribute it and or modify it under either the terms of the (?:2 clause bsdl|gpl)"),
    ("bsd", r"use of this source code is governed by an? bsd style license that can be found in the license file"),
    ("mit", r"use of this source code is governed by an? mit style license that can be found in the license file"),
    ("apache-2.0", r"use of this source code is governed by the apache 2 0 license that can be found in the license file"),
    ("bsl-1.0", r"distributed under the boost software license version 1 0"),
    ("bsl-1.0", r"www boost org license 1 0"),
    ("mit", r"(?:https?|www) (?:www )?opensource org licenses mit"),
    ("bsd", r"opensource org licenses bsd"),
    ("isc", r"opensource org licenses isc"),
    ("zlib", r"opensource org licenses zlib"),
    ("artistic-2.0", r"opensource org licenses artistic"),
    ("ofl-1.1", r"this font software is licensed under the sil open font license version 1 1"),
    ("ofl-1.1", r"scripts sil org ofl"),
    ("ofl-1.1", r"openfontlicense org"),
    ("lppl", r"may be distributed and or modified under the conditions of the latex project public license"),
    ("lppl", r"this work has the lppl maintenance status"),
    ("zope", r"this software is subject to the provisions of the zope public license"),
    ("ms-pl", r"subject to the microsoft public license"),
    ("mulanpsl-2.0", r"you can use this software according to the terms and conditions of the mulan psl"),
    ("unicode", r"unicode inc license agreement data files and software"),
    ("nasa", r"nasa open source agreement version 1 3"),
    ("vim", r"vim is charityware"),
    ("w3c", r"w3c software (?:and document )?notice and license"),
    ("cc-by", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution(?: [1-4] [05])?(?: international| unported| generic)? licen[sc]e"),
    ("cc-by-sa", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution share ?alike"),
    ("cc-by-nc", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution non ?commercial(?: [1-4] [05])?(?: international| unported| generic)? licen[sc]e"),
    ("cc-by-nd", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution no ?deriv(?:ative)?s"),
    ("cc-by-nc-sa", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution non ?commercial share ?alike"),
    ("cc-by-nc-nd", r"this (?:work|article|document|text|page|dataset|book|material) is licensed under (?:a |the )?creative commons attribution non ?commercial no ?deriv(?:ative)?s"),
    ("cc-by", r"creativecommons org licenses by(?= [1-4])"),
    ("cc-by-sa", r"creativecommons org licenses by sa"),
    ("cc-by-nc", r"creativecommons org licenses by nc(?= [1-4])"),
    ("cc-by-nd", r"creativecommons org licenses by nd"),
    ("cc-by-nc-sa", r"creativecommons org licenses by nc sa"),
    ("cc-by-nc-nd", r"creativecommons org licenses by nc nd"),
    ("cc0", r"creativecommons org publicdomain zero"),
    ("public-domain", r"creativecommons org publicdomain mark"),
    ("cc-by-sa", r"text is available under the creative commons attribution share ?alike"),
    ("cc-by", r"(?:open access article|article) distributed under the terms (?:and conditions )?of the creative commons attribution(?: non ?commercial)?"),
    ("odbl", r"is made available under the open database license"),
    ("odc-by", r"is made available under the open data commons attribution license"),
    ("pddl", r"is made available under the public domain dedication and license"),
    ("dbcl", r"any rights in individual contents of the database are licensed under the database contents license"),
    ("ogl", r"contains public sector information licensed under the open government licence"),
    ("polyform", r"polyform (?:noncommercial|small business|shield|strict|perimeter|internal use|free trial) license"),
    ("commons-clause", r"commons clause license condition v1 0"),
    ("busl-1.1", r"use of this software is governed by the business source license"),
    ("elastic-2.0", r"licensed under the elastic license(?: 2 0)?"),
    ("sspl", r"licensed under the server side public license"),
    ("llama", r"is licensed under the (?:meta )?llama(?: [2-4](?: [0-9])?)? community license"),
    ("gemma", r"gemma is provided under and subject to the gemma terms of use"),
    ("dual", r"(?:dual|multi) licensed under(?: the)?(?: terms of)?(?: \S+){1,4}? (?:and|or) (?:the )?(?:gpl|mit|apache|bsd|lgpl|mpl)"),
    ("public-domain", r"this (?:file|software|code|work|program|document|text) is in the public domain"),
    ("public-domain", r"(?:has been |is |was )?(?:placed|released) in(?:to)? the public domain"),
    ("public-domain", r"no copyright is claimed"),
    ("public-domain", r"is a work of the (?:u s|us|united states) government and is not subject to copyright protection"),
    ("public-domain", r"the author(?:s)? hereby disclaims? copyright to this source code"),
    ("proprietary", r"unauthorized (?:copying|use|distribution|reproduction)(?: \S+){0,10}? (?:is )?(?:strictly )?prohibited"),
    ("proprietary", r"this is unpublished proprietary source code"),
    ("proprietary", r"the copyright notice above does not evidence any actual or intended publication"),
    ("proprietary", r"is the confidential and proprietary information of"),
    ("proprietary", r"no part of this (?:publication|book|document|work|software) may be reproduced"),
    ("proprietary", r"may not be (?:copied|reproduced)(?: \S+){0,8}? without (?:the )?(?:prior |express )?(?:written )?permission"),
    ("proprietary", r"may not be (?:published|broadcast)(?: broadcast)? rewritten or redistributed"),
    ("proprietary", r"contains(?: \S+){0,6}? proprietary (?:information|and confidential|data|trade secrets)"),
    ("proprietary", r"licensed (?:exclusively|solely) to"),
    ("eula", r"end user licen[sc]e agreement"),
    ("eula", r"this is a legal agreement between you"),
    ("eula", r"oracle binary code license agreement"),
    ("eula", r"oracle no fee terms and conditions"),
    ("noncommercial", r"for non ?commercial(?: \S+){0,3}? use only"),
    ("see-license", r"see(?: the)?(?: accompanying| included| enclosed)? license(?: txt| md)?(?: file)? for (?:details|more details|the full|full|more information|license information)"),
    ("see-license", r"(?:license|licence) that can be found in the license file"),
    ("see-license", r"distributed under the same license as"),
)

_GROUP = re.compile(r"\((?:[^()]|\([^()]*\))*\)(?:\{[0-9,]+\}\??|[?*+])?")


def literal(pattern: str) -> str:
    """The longest run of characters outside groups, classes and options: every match holds it."""
    plain = re.sub(r"\[[^\]]*\][?*+]?|\\S\+?|.[?*]", "\0", _GROUP.sub("\0", pattern))
    return max(plain.split("\0"), key=len)
