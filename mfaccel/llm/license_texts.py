"""Sentences and notices of well-known licences, by family, and sentences about rights that name none of them."""

TEMPLATES = {
    "apache-2.0": [
        "Licensed under the Apache License, Version 2.0", "you may not use this file except in compliance with the License", "SPDX-License-Identifier: Apache-2.0",
        "distributed under the terms of the Apache License 2.0", "Apache License Version 2.0, January 2004",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied",
    ],
    "mit": [
        "Released under the MIT License", "SPDX-License-Identifier: MIT", "This project is licensed under the terms of the MIT license", "MIT License", "The MIT License (MIT)",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
        "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software",
    ],
    "gpl-3.0": [
        "This work is licensed under the GNU General Public License, version 3", "SPDX-License-Identifier: GPL-3.0-or-later", "licensed under the GPLv3", "Distributed under GPLv3", "GNU GPL v3 or later", "SPDX-License-Identifier: GPL-3.0-only",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License",
    ],
    "gpl-2.0": [
        "licensed under the GNU General Public License, version 2", "SPDX-License-Identifier: GPL-2.0-only", "licensed under the GPLv2", "Distributed under GPLv2", "GNU GPL v2", "SPDX-License-Identifier: GPL-2.0-or-later",
        "under the terms of the GNU General Public License version 2 as published by the Free Software Foundation",
    ],
    "agpl-3.0": ["licensed under the GNU Affero General Public License, version 3", "SPDX-License-Identifier: AGPL-3.0-or-later", "Distributed under AGPLv3", "under the terms of the GNU Affero General Public License as published by the Free Software Foundation"],
    "lgpl": ["licensed under the GNU Lesser General Public License", "SPDX-License-Identifier: LGPL-2.1-or-later", "SPDX-License-Identifier: LGPL-3.0-only", "Distributed under LGPLv3", "under the terms of the GNU Lesser General Public License as published by the Free Software Foundation"],
    "mpl-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "SPDX-License-Identifier: MPL-2.0", "licensed under the Mozilla Public License 2.0", "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/"],
    "epl-2.0": ["Licensed under the Eclipse Public License 2.0", "SPDX-License-Identifier: EPL-2.0", "This program and the accompanying materials are made available under the terms of the Eclipse Public License v. 2.0"],
    "eupl-1.2": ["Licensed under the European Union Public Licence, version 1.2", "SPDX-License-Identifier: EUPL-1.2", "Licensed under the EUPL"],
    "bsd": [
        "Released under the BSD 3-Clause License", "Released under the BSD 2-Clause License", "SPDX-License-Identifier: BSD-3-Clause", "SPDX-License-Identifier: BSD-2-Clause",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer",
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    ],
    "isc": ["Released under the ISC License", "SPDX-License-Identifier: ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"],
    "zlib": ["Released under the zlib License", "SPDX-License-Identifier: Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software"],
    "boost-1.0": ["Distributed under the Boost Software License, Version 1.0", "SPDX-License-Identifier: BSL-1.0"],
    "unlicense": ["This is free and unencumbered software released into the public domain", "SPDX-License-Identifier: Unlicense", "Released under the Unlicense"],
    "ofl-1.1": ["This Font Software is licensed under the SIL Open Font License, Version 1.1", "SPDX-License-Identifier: OFL-1.1"],
    "artistic-2.0": ["licensed under the Artistic License 2.0", "SPDX-License-Identifier: Artistic-2.0"],
    "cc0": ["released into the public domain under CC0 1.0 Universal", "To the extent possible under law the author has waived all copyright and related rights", "SPDX-License-Identifier: CC0-1.0", "CC0 1.0 Universal"],
    "cc-by-4.0": ["Licensed under CC BY 4.0", "CC BY 4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License", "SPDX-License-Identifier: CC-BY-4.0"],
    "cc-by-sa-4.0": ["Licensed under CC BY-SA 4.0", "CC BY-SA 4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License", "SPDX-License-Identifier: CC-BY-SA-4.0"],
    "cc-by-nc-4.0": ["Licensed under CC BY-NC 4.0", "CC BY-NC 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License", "SPDX-License-Identifier: CC-BY-NC-4.0"],
    "cc-by-nd-4.0": ["Licensed under CC BY-ND 4.0", "CC BY-ND 4.0", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License", "SPDX-License-Identifier: CC-BY-ND-4.0"],
}

OTHERS = [
    "All rights reserved", "Copyright of the author, all rights reserved", "You need a licence to drive a car", "He asked for permission to leave the room",
    "The warranty covers parts and labour for two years", "This software is proprietary and confidential, redistribution is prohibited",
    "Licensed under the terms of the commercial agreement between the parties", "The public domain is a legal concept", "a fishing license costs ten dollars",
    "Copyright 2020 Example Corporation", "the city council will license street vendors", "without permission of the publisher",
    "Licensed under the House Rules of the club, edition 7", "Released under the terms of the reader agreement", "This work is licensed under a custom license, version 1",
    "gnu are large antelopes", "no warranty is given", "the copyright page of the book", "licensed electrician with ten years of work",
    "No part of this publication may be reproduced or transmitted in any form without the prior written permission of the publisher",
    "This license agreement is between you and the company and governs your use of the product", "Use of this source code is governed by the license of the company",
    "students at the MIT asked for a licence", "Das Haus mit der Lizenz", "SPDX-License-Identifier: LicenseRef-Internal", "free of charge for members", "The software is licensed, not sold", "Redistribution of this newsletter is welcome",
]

#: Made-up licences, from which notices of the class "unknown" are put together.
UNKNOWN_NAMES = ["Harbour", "Violet", "Northwind", "Granite", "Acme Widget", "River Delta", "Copperfield", "Open Orchard", "Lantern", "Meadow"]
UNKNOWN_FORMS = ["Licensed under the {} Public License {}", "Licensed under the {} License, Version {}", "Released under the {} License", "This work is licensed under the {} Community License, version {}", "distributed under the terms of the {} License {}", "SPDX-License-Identifier: {}-{}"]
