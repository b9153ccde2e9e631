"""Labels of relatives, and the join against all blocks."""

from __future__ import annotations

import random

import duckdb
from conftest import same_rows

from pathalgebra.llm import licenses

LINES = {
    "Licensed under CC BY 4.0.": "cc-by",
    "Licensed under CC BY-NC 4.0.": "cc-by,cc-by-nc-4.0",
    "Licensed under CC BY-SA 4.0.": "cc-by,cc-by-sa-4.0",
    "Released under the BSD license": "bsd-named",
    "the license you released was under review": "",
    "Released under the MIT License.": "mit",
    "you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation": "gpl,gpl-notice",
    "it under the terms of the GNU Lesser General Public License as published by": "gpl,lgpl",
    "der Hund mit\nthe license": "",
    "ReleaSed under the KIT License": "",  # the Kelvin sign isn't folded
}


def test_relatives(spark):
    rows = spark.createDataFrame(list(enumerate(LINES)), "doc_id long, text string")
    got = {r.doc_id: r.labels for r in licenses.license_scan(rows).collect()}
    assert [got[i] for i in range(len(LINES))] == list(LINES.values())


def test_join_finds_what_all_blocks_say(spark):
    rng = random.Random(4)
    words = [w for t in licenses.TEMPLATES for w in t[1].split()]
    texts = []
    for k in range(150):
        said = rng.choice(licenses.TEMPLATES)[1].split()
        for _ in range(rng.randrange(4)):  # words that are missing, strange or in between
            said[rng.randrange(len(said))] = rng.choice(["", "other", rng.choice(words)])
        noise = [rng.choice(words) for _ in range(rng.randrange(60))]
        texts.append((k % 140, rng.choice([" ", "\n", ", "]).join(noise + said + noise[:5])))
    rows = spark.createDataFrame([*texts, (None, None), (None, "")], "doc_id long, text string")
    connection = duckdb.connect()
    connection.register("documents", rows.toArrow())
    same_rows(licenses.license_scan(rows), connection, licenses.sql())
