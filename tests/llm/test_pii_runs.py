"""Cards and IBANs beside other numbers and words."""

from pyspark.sql import functions as F

from ripplegraph.llm import op8_pii as op8

CARD, IBAN = "4111 1111 1111 1111", "ES91 2100 0418 4502 0005 1332"


def test_neighbours_do_not_hide_cards_and_ibans(spark):
    texts = [f"{CARD} 12/26", f"{CARD} 123", f"2024 {CARD}", f"{CARD} 5500 0000 0000 0004", f"{IBAN} EUR", f"{IBAN} PAID {CARD}", f"{CARD} 2024-02-29", f"7 {CARD} 10.0.200.3", CARD, IBAN, "1 2 3 " * 4000 + "x"]
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    out = {r.doc_id: r.text for r in op8.pseudonymise(frame).collect()}
    card, iban = out[8], out[9]
    assert card != CARD and iban != IBAN and out[10] == texts[10]
    assert [out[i] for i in (0, 1, 2, 4, 5)] == [f"{card} 12/26", f"{card} 123", f"2024 {card}", f"{iban} EUR", f"{iban} PAID {card}"]
    assert out[3].startswith(card) and "5500 0000 0000 0004" not in out[3]
    assert out[6].startswith(card) and "2024-02-29" not in out[6] and out[7].startswith(f"7 {card} ") and "10.0.200.3" not in out[7]
    assert spark.createDataFrame([(out[3][20:],)], "v string").where(op8.luhn_sum(F.regexp_replace("v", " ", "")) % 10 == 0).count() == 1
