"""Notices that are wrapped over lines, and licenses that one word tells apart."""

import pytest

from tupleshare.llm import license_scan

CASES = [
    ("Redistribution and use in source and binary forms, with or without\nmodification, are permitted", "bsd"),
    ("# Permission to use, copy, modify, and/or distribute this software\n# for any purpose with or without fee\n# is hereby granted", "isc"),
    ("some words before\nReleased under\nthe MIT\nLicense", "mit"),
    ("Released under the\n\nMIT License", ""),
    ("Licensed under the GNU General Public License", "gpl"),
    ("Licensed under the GNU Affero General\nPublic License", "agpl,gpl"),
    ("Licensed under the GNU Lesser General Public License", "gpl,lgpl"),
]


def test_labels(spark):
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(CASES)], "doc_id long, text string")
    got = {r.doc_id: r for r in license_scan.scan_licenses(df).collect()}
    assert [got[i].labels for i in range(len(CASES))] == [want for _, want in CASES]
    assert got[0].score == pytest.approx(1.0)
