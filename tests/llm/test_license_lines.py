"""License statements that are wrapped over lines."""

from __future__ import annotations

from pathalgebra.llm import licenses

BSD = "Redistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions are met:"
MIT = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software"


def test_wrapped_statements(spark):
    texts = [
        BSD, "/*\n * " + BSD.replace("\n", "\n * ") + "\n */", "\n".join(MIT.split()), "\n\n".join(MIT.split()), "x y\n" * 40 + MIT.replace(" to ", " to\r\n"),
        "Redistribution and use in source and binary forms, with or without\n" + "other words\n" * 9 + "modification, are permitted", "plain\n\ntext", "",
        "Redistribution and use in source and binary forms, with or without modification, are permitted",
        "der den mit.\nLicensed under the Apache License, Version 2.0.",
    ]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r for r in licenses.license_scan(rows).collect()}
    assert [got[i].labels for i in range(len(texts))] == ["bsd", "bsd", "mit-text", "mit-text", "mit-text", "", "", "", "bsd", "apache-2.0"]
    assert [got[i].score for i in (0, 2, 5, 8)] == [1.0, 1.0, 0.0, 1.0]
