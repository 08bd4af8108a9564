"""Every keyword of a license rule stands in whatever its pattern matches, however the text is wrapped."""

import pytest

from rpqframe.llm import licenses

CASES = {
    "GNU{}General{}Public{}License version 2": "gpl-2.0",
    "released into the public{}domain": "public-domain",
    "creative{}commons attribution 4.0": "cc-by-4.0",
    "permission is{}hereby granted, free of charge, to any person obtaining a{}copy": "mit-text",
    "all rights{}reserved": "proprietary",
    "GNU lesser{}general{}public license v3": "lgpl-3.0",
    "GNU library{}general{}public license": "lgpl-2.0",
    "GNU free{}documentation{}license": "gfdl",
    "common{}development{}and distribution license": "cddl",
    "common{}public{}license": "cpl",
    "european{}union{}public license": "eupl",
    "creative{}commons license": "cc-any",
    "open{}font{}license": "ofl",
    "microsoft{}public{}license": "ms-pl",
    "microsoft{}reciprocal license": "ms-rl",
    "open{}database license": "odbl",
    "open{}software{}license": "osl-3.0",
    "academic{}free license": "afl-3.0",
}


@pytest.mark.parametrize("blank", [" ", "\n", "  ", "\r\n\t"])
def test_blanks_between_words(spark, blank):
    rows = [(k, "see " + t.replace("{}", blank) + " here") for k, t in enumerate(CASES)]
    got = {x.doc_id: x.labels.split(",") for x in licenses.scan(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert [label for k, label in enumerate(CASES.values()) if label not in got[k]] == []
