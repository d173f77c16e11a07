"""Licenses beside others and over line ends."""

from factlake.llm import licenses


def test_licenses_beside_others_and_over_lines(spark):
    texts = [
        "Licensed under the Apache License, Version 2.0 or the MIT license",
        "Redistribution and use in source and binary forms, with or without\nmodification, are permitted",
        "x\nThis Source Code Form is subject to the terms of the Mozilla Public\n * License, v. 2.0. If a copy",
        "This work is licensed under the GNU General Public License\nversion 3",
        "released\nunder " + "far " * 50 + "the\nmit license",
    ]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: (r["labels"], r["lines"]) for r in licenses.scan(df).collect()}
    assert got[0] == ("apache-2.0,mit", [0]) and got[1] == ("bsd", [0, 1]) and got[2] == ("mpl-2.0", [1, 2])
    assert got[3] == ("gpl,gpl-3.0", [0, 1]) and got[4] == ("", [])
