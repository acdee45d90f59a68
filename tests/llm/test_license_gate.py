"""The keywords of a signature have to be implied by its pattern."""

import random
import re
from re import _parser

from peakgroups.llm import licenses

TEXTS = [
    ("SPDX-License-Identifier: MPL-2.0", "mpl"), ("SPDX-License-Identifier: EPL-2.0", "epl"), ("SPDX-License-Identifier: PSF-2.0", "psf"),
    ("SPDX-License-Identifier: BSL-1.0", "boost"), ("SPDX-License-Identifier: GFDL-1.3", "gfdl"), ("SPDX-License-Identifier: PDDL-1.0", "public-domain"),
    ("SPDX-License-Identifier: CC-BY-SA-4.0", "cc-by,cc-by-sa"), ("Attribution-Share Alike 4.0", "cc-by-sa"), ("Attribution Non-Commercial", "cc-by-nc"),
    ("SIL Open Font License 1.1", "ofl"), ("see the GPLv3", "gpl"), ("see the AGPL3", "agpl"),
    ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software and so on", "mit"),
    ("Redistribution and use in source and binary forms, with or without modification, are permitted", "bsd"),
]


def some_match(rng, parsed):
    out = ""
    for op, arg in parsed:
        name = str(op)
        if name == "LITERAL":
            out += chr(arg)
        elif name == "SUBPATTERN":
            out += some_match(rng, arg[3])
        elif name == "BRANCH":
            out += some_match(rng, rng.choice(arg[1]))
        elif name == "MAX_REPEAT":
            out += "".join(some_match(rng, arg[2]) for _ in range(rng.randint(arg[0], arg[1])))
        elif name == "IN":
            kind, value = rng.choice(arg)
            out += rng.choice("0123456789") if str(kind) == "CATEGORY" else chr(rng.randint(*value)) if str(kind) == "RANGE" else chr(value)
        else:
            raise ValueError(name)
    return out


def test_keywords_hold_in_all_matches():
    rng = random.Random(3)
    for s in licenses.signatures():
        for _ in range(60):
            text = f" {some_match(rng, _parser.parse(s.pattern))} "
            assert re.search(f"(?<= )(?:{s.pattern})(?= )", text)
            assert any(f" {k} " in text for k in s.keywords) and re.search(licenses.WORDED, text), (s, text)


def test_gate_lets_detections_through(spark):
    d = spark.createDataFrame(list(enumerate(t for t, _ in TEXTS)), "doc_id long, text string")
    got = {r.doc_id: (r.labels, r.score > 0) for r in licenses.scan(d).collect()}
    assert got == {i: (label, True) for i, (_, label) in enumerate(TEXTS)}
