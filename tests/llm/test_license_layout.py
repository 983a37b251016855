"""Licences as they are printed: in paragraphs, inside a longer document."""

from facetspark.llm import license_scan

CUTS = {
    "MIT text": ("The above copyright notice and", "THE SOFTWARE IS"),
    "BSD-2-Clause full text": ("1. Redis", "2. Redis", "THIS SOFTWARE IS"),
    "BSD-3-Clause full text": ("1. Redis", "2. Redis", "3. Neither", "THIS SOFTWARE IS"),
    "ISC full text": ("THE SOFTWARE IS",),
}


def test_templates_in_their_layout(spark):
    other = "\n\n".join(f"paragraph {k} of {k + 1} about number {k * k} and nothing else" for k in range(60))
    rows = []
    for name, cuts in CUTS.items():
        text = license_scan.TEMPLATES[name]
        for cut in cuts:
            assert text.count(cut) == 1
            text = text.replace(cut, f"\n\n{cut}")
        rows.append((name, f"{other}\n\n{text}\n\n{other}"))
    got = {r["doc_id"]: r["licenses"] for r in license_scan.scan_licenses(spark.createDataFrame([*rows, ("none", other)], "doc_id string, text string")).collect()}
    assert got["none"] == []
    assert all(name in got[name] for name in CUTS), got
