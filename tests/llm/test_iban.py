"""IBANs before words in capitals and digits."""

from laneforge.llm import pii


def test_iban_before_capitals(spark):
    de, gb = "DE89370400440532013000", "GB82 WEST 1234 5698 7654 32"
    texts = {f"IBAN {de} Bitte zahlen": [de], f"IBAN: {gb} Please pay": [gb], f"{de} BIC COBADEFFXXX": [de], f"{de} 12 {gb} 7": [de, gb], f"{de} {gb} END": [de, gb], f"{de}X": [], f"x{de} Y": [], f"{de[:-1]}1 Bitte": [], "NO93 8601 1117 947 KID 5": ["NO93 8601 1117 947"]}
    rows = list(enumerate(texts))
    got = {r["id"]: [rows[r["id"]][1][s["start"] : s["end"]] for s in r["iban"]] for r in pii.spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: texts[t] for i, t in rows}
