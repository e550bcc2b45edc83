"""Licences and notices as templates.

[...] may be missing, its alternatives are parted by |, and regions may stand within regions; {a-b} stands for a to b words of any kind.
All else must be there word for word; case, punctuation and line breaks do not count. Long licences are known by the notice that they
ask for in each file, short ones by their whole text.
"""

_AS_IS = "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and [non infringement|noninfringement]"
_LIABLE = "in no event shall {1-10} be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software"
_GRANT = "permission is hereby granted free of charge to any person obtaining a copy of {1-6} and associated documentation files [the software] to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so"
_BSD = "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"
_SOURCE = "[1|a] redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"
_BINARY = "[2|b] redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution"
_HOLDERS = "this software is provided by {1-10} as is and any express or implied warranties including but not limited to the implied warranties of merchantability and fitness for a particular purpose are disclaimed in no event shall {1-10} be liable for any direct indirect incidental special exemplary or consequential damages including but not limited to procurement of substitute goods or services loss of use data or profits or business interruption however caused and on any theory of liability whether in contract strict liability or tort including negligence or otherwise arising in any way out of the use of this software even if advised of the possibility of such damage"
_FREE = "is free software [:] you can redistribute it and or modify it under the terms of the gnu"
_BY_FSF = "[general] public license as published by the free software foundation [;]"
_PERMIT = "permission to use copy modify and [or] distribute this software for any purpose with or without fee is hereby granted"
_AUTHOR = "the software is provided as is and the author disclaims all warranties with regard to this software including all implied warranties of merchantability and fitness in no event shall the author be liable for any special direct indirect or consequential damages or any damages whatsoever resulting from loss of use data or profits whether in an action of contract negligence or other tortious action arising out of or in connection with the use or performance of this software"

TEMPLATES: dict[str, list[str]] = {
    "mit": [f"{_GRANT} subject to the following conditions the above copyright notice and this permission notice [including the next paragraph] shall be included in all copies or substantial portions of the software {_AS_IS} {_LIABLE}"],
    "mit-0": [f"{_GRANT} {_AS_IS} {_LIABLE}"],
    "x11": [f"{_GRANT} subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software {_AS_IS} in no event shall {{1-6}} be liable for any claim damages or other liability whether in an action of contract tort or otherwise arising from out of or in connection with the software or the use or other dealings in the software except as contained in this notice the name of {{1-6}} shall not be used in advertising or otherwise to promote the sale use or other dealings in this software without prior written authorization from {{1-6}}"],
    "mit-notice": ["[released|licensed|distributed|available] under the [terms of the] mit license"],
    "isc": [f"{_PERMIT} provided that the above copyright notice and this permission notice appear in all copies {_AUTHOR}"],
    "0bsd": [f"{_PERMIT} {_AUTHOR}"],
    "bsd-2-clause": [f"{_BSD} {_SOURCE} {_BINARY} {_HOLDERS}"],
    "bsd-3-clause": [f"{_BSD} {_SOURCE} {_BINARY} [3|c] neither the name of {{1-10}} nor the names of [its|any|the] [contributors|{{1-4}} contributors] may be used to endorse or promote products derived from this software without specific prior written permission {_HOLDERS}"],
    "zlib": ["this software is provided as is without any express or implied warranty in no event will the [author|authors|{1-4}] be held liable for any damages arising from the use of this software permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions [1] the origin of this software must not be misrepresented you must not claim that you wrote the original software if you use this software in a product an acknowledgment in the product documentation would be appreciated but is not required [2] altered source versions must be plainly marked as such and must not be misrepresented as being the original software [3] this notice may not be removed or altered from any source distribution"],
    "unlicense": ["this is free and unencumbered software released into the public domain anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means [in jurisdictions that recognize copyright laws the author or authors of this software dedicate any and all copyright interest in the software to the public domain [we make this dedication for the benefit of the public at large and to the detriment of our heirs and successors] [we intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law]] the software is provided as is"],
    "bsl-1.0": ["permission is hereby granted free of charge to any person or organization obtaining a copy of the software and accompanying documentation covered by this license the software to use reproduce display distribute execute and transmit the software and to prepare derivative works of the software and to permit third parties to whom the software is furnished to do so all subject to the following"],
    "wtfpl": ["do what the fuck you want to public license [terms and conditions for copying distribution and modification] [0] you just do what the fuck you want to"],
    "postgresql": ["permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement is hereby granted provided that the above copyright notice and this paragraph and the following two paragraphs appear in all copies"],
    "beerware": ["as long as you retain this notice you can do whatever you want with this stuff if we meet some day and you think this stuff is worth it you can buy me a beer in return"],
    "apache-2.0": [
        "licensed under the [terms of the] apache license [,] version 2 [0]",
        "licensed under [the] apache 2 0",
        "licensed under the apache license version 2 0 the license you may not use [this file|{1-6}] except in compliance with the license [you may obtain a copy of the license at {1-12}] unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    ],
    "gpl-3.0": ["[licensed] under the [terms of the] gnu general public license [as published by the free software foundation] [either] version 3 [or later]"],
    "gpl-2.0": [f"{_FREE} {_BY_FSF} [either] version 2 [of the license [or at your option any later version]]", "[licensed] under the [terms of the] gnu general public license [as published by the free software foundation] [either] version 2 [or later]"],
    "gpl-notice": [f"{{1-4}} {_FREE} general public license"],
    "lgpl-2.1": [f"{_FREE} lesser general public license as published by the free software foundation [either] version 2 1 [of the license [or at your option any later version]]"],
    "lgpl-3.0": [f"{_FREE} lesser general public license as published by the free software foundation [either] version 3 [of the license [or at your option any later version]]"],
    "agpl-3.0": [f"{_FREE} affero general public license as published by the free software foundation [either] version 3 [of the license [or at your option any later version]]"],
    "mpl-2.0": ["this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at {1-8}"],
    "epl-2.0": ["this program and the accompanying materials are made available under the terms of the eclipse public license [v 2 0|2 0] [which [accompanies this distribution and] is available at]"],
    "cc0-1.0": ["to the extent possible under law {1-12} has [waived|dedicated] all copyright and related or neighboring rights to [this work|{1-8}]", "[licensed|released|dedicated] under [the] [creative commons] cc0 1 0"],
    "cc-by-4.0": ["licensed under [a|the] [creative commons] cc by 4 0", "licensed under [a|the] creative commons attribution 4 0 [international] license"],
    "cc-by-sa-4.0": ["licensed under [a|the] [creative commons] cc by sa 4 0", "licensed under [a|the] creative commons attribution sharealike 4 0 [international] license"],
    "cc-by-nc-4.0": ["licensed under [a|the] [creative commons] cc by nc 4 0", "licensed under [a|the] creative commons attribution noncommercial 4 0 [international] license"],
    "bsd-notice": ["[released|licensed|distributed|available] under [the|a] [terms of the] [new|modified|simplified|2 clause|3 clause] bsd license"],
}
