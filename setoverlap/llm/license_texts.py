"""Characteristic passages of public licences: whole short licences by paragraph, notices of the long ones, and mentions."""

from __future__ import annotations

# Fixed values: (label, passage, mandatory key phrases); words are compared in lower case, punctuation is not.
PASSAGES: list[tuple[str, str, tuple[str, ...]]] = [
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:", ("hereby granted free of charge",)),
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files", ("hereby granted free of charge",)),
    ("mit", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.", ("permission notice shall be included",)),
    ("mit", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY", ("purpose and noninfringement",)),
    ("mit", "released under the MIT License", ("mit license",)),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.", ("with or without fee",)),
    ("isc", "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS.", ("author disclaims all warranties",)),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:", ("source and binary forms",)),
    ("bsd", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.", ("must retain the above copyright notice",)),
    ("bsd", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.", ("must reproduce the above copyright notice",)),
    ("bsd", "may be used to endorse or promote products derived from this software without specific prior written permission", ("endorse or promote products",)),
    ("zlib", "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:", ("alter it and redistribute it freely",)),
    ("unlicense", "This is free and unencumbered software released into the public domain.", ("unencumbered software released into the public domain",)),
    ("unlicense", "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.", ("anyone is free to copy modify publish",)),
    ("boost", "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license", ("person or organization obtaining a copy",)),
    ("apache", "Licensed under the Apache License, Version 2.0", ("apache license version 2 0",)),
    ("apache", "you may not use this file except in compliance with the License. You may obtain a copy of the License at", ("except in compliance with the license",)),
    ("apache", "you may not use this file except in compliance with the License", ("except in compliance with the license",)),
    ("apache", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.", ("warranties or conditions of any kind",)),
    ("gpl", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", ("gnu general public license",)),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the GNU General Public License", ("gnu general public license",)),
    ("gpl", "You should have received a copy of the GNU General Public License along with this program.", ("copy of the gnu general public license",)),
    ("gpl", "this work is licensed under the GNU General Public License version 3", ("gnu general public license",)),
    ("lgpl", "you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation", ("gnu lesser general public license",)),
    ("lgpl", "licensed under the terms of the GNU Lesser General Public License", ("gnu lesser general public license",)),
    ("agpl", "you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation", ("gnu affero general public license",)),
    ("agpl", "licensed under the terms of the GNU Affero General Public License", ("gnu affero general public license",)),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at", ("mozilla public license",)),
    ("mpl", "this source code form is subject to the terms of the Mozilla Public License v 2 0", ("mozilla public license",)),
    ("epl", "This program and the accompanying materials are made available under the terms of the Eclipse Public License", ("eclipse public license",)),
    ("artistic", "you may redistribute this package under the terms of the Artistic License", ("artistic license",)),
    ("cc0", "The person who associated a work with this deed has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law", ("dedicated the work to the public domain",)),
    ("cc-by", "This work is licensed under a Creative Commons Attribution 4.0 International License.", ("creative commons attribution 4 0",)),
    ("cc-by-sa", "This work is licensed under a Creative Commons Attribution ShareAlike 4.0 International License.", ("attribution sharealike",)),
    ("cc-by-nc", "This work is licensed under a Creative Commons Attribution NonCommercial 4.0 International License.", ("attribution noncommercial",)),
    ("cc-by-nc", "licensed under CC BY NC 4.0", ("cc by nc",)),
]
