"""Published sample links of a raw list with a reference list, and what an outside geocoder made of the raw address."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: Number, raw address, reference addresses that tie for the best, printed score, the geocoder's answer (None: not found).
SAMPLE_LINKS = (
    (1, "33 34-38 EHMNTV DIU NSW 6561", ("UNIT 33 34-38 EHMNTV STRET OUT DIR NSW 6561",), 0.88, "33/34-38 EHMNTV ST OUT DIU NSW 6561"),
    (2, "53 741 ADGNR EFORST AKLR QLD 9368", ("UNIT 53 741 ADGNR AVENUE EFORST LAKE QLD 9168",), 0.80, "53/741 ADGNR AVE EFORST AEKL QLD 9168"),
    (3, "972 4 CEOPRW LMOW NEW WALES 5133", ("UNIT 972 4 CEOPRW AFHRW ROADWAY LMOW NSW 5133",), 0.90, None),
    (4, "713 311 GUN HILNU ACT 5035", ("UNIT 731 311 GUN PLACE HILNU ACT 5035", "UNIT 713 311 GUN PLACE HILNU ACT 5035", "UNIT 317 311 GUN PLACE HILNU ACT 5035"), 0.93, "713/311 GUN PL HILNU ACT 5035"),
    (5, "3 59 FGIS DEKNOR QLD QLD 9173", ("UNIT 3 59 FGIS STRET DEKNOR QLD 9173",), 0.90, "3/59 FGIS ST DEKNOR QLD 9173"),
    (6, "9 NO 7 TO 2 CELMNT ADEGNO VIC 7362", ("UNIT 9 7-2 CELMNT STRET ADEGNO VIC 7362",), 0.91, None),
    (7, "313 0 EGKNORW ABEHILTZ BAY 5133", ("UNIT 313 0 EGKNORW AVENUE ABEHILTZ BAY NSW 5133",), 0.91, "313/0 EGKNORW AVE ABEHILTZ BAY NSW 5133"),
    (8, "MARGETIC 6 715 ABDFORST BELMNORU VIC 7123", ("FLAT 6 715 ABDFORST STRET HNORT BELMNORU VIC 7123",), 0.92, None),
    (9, "43 3345 ACDHINSV AGRTV QLD 9355", ("UNIT 43 3345 ACDEHINSV ROAD MOUNT AGRTV EAST QLD 9355",), 0.82, "43/3345 ACDEHINSV RD MOUNT AGRTV EAST QLD 9355"),
    (10, "78 03 ADELMNOR BELM VIC VIC 7133", ("UNIT 78 03 ADELMNOR STRET ACFORSTY VIC 7133",), 0.83, "78/03 ADELMNOR ST ACFORSTY VIC 7133"),
)


def sample_rows() -> tuple[list[tuple], list[tuple], list[tuple]]:
    """``id, address`` of both sides (reference ids: ten times the link's number, and up), and ``id, printed, external``."""
    left = [(n, raw) for n, raw, *_ in SAMPLE_LINKS]
    right = [(10 * n + k, text) for n, _, texts, *_ in SAMPLE_LINKS for k, text in enumerate(texts)]
    return left, right, [(n, printed, external) for n, _, _, printed, external in SAMPLE_LINKS]


def sample_lists(spark: SparkSession) -> tuple[DataFrame, DataFrame, DataFrame]:
    left, right, answers = sample_rows()
    address = "id long, address string"
    return spark.createDataFrame(left, address), spark.createDataFrame(right, address), spark.createDataFrame(answers, "id long, printed double, external string")
