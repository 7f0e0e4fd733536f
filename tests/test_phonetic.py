"""Codes equal those of the JVM encoders that Spark ships with."""

import random

import pytest
from pyspark.sql import functions as F

from dnfblock.functions import phonetic
from dnfblock.functions.indexing import REGISTRY

WORDS = """beats knight mackenzie phillips schmidt thompson tymczak wright hughes laugh tough enough trough comb gnome wheel
xavier school rice ledge lemmings yes jay quick hannah though rough lead evening heavy knock machine scratch almond antique azure
beige bisque blanched blush burlywood chartreuse chiffon cornflower dodger firebrick frosted ghost honeydew khaki lavender maroon
midnight moccasin orchid papaya peach powder puff rosy saddle sienna smoke spring thistle tomato turquoise""".split()
ENCODERS = {
    "refined_soundex": "RefinedSoundex", "nysiis": "Nysiis", "caverphone1": "Caverphone1", "caverphone2": "Caverphone2",
    "match_rating": "MatchRatingApproachEncoder", "cologne": "ColognePhonetic",
}


@pytest.mark.parametrize("name", ENCODERS)
def test_chain_equals_encoder(spark, name):
    kind = getattr(spark._jvm.org.apache.commons.codec.language, ENCODERS[name])
    encoder = kind(False) if name == "nysiis" else kind()
    rows = spark.createDataFrame([(w,) for w in WORDS], "w string").select("w", getattr(phonetic, name)(F.col("w")).alias("c")).collect()
    assert [(r.w, r.c) for r in rows] == [(r.w, encoder.encode(r.w)) for r in rows]


def test_soundex_and_metaphone(spark):
    language = spark._jvm.org.apache.commons.codec.language
    rows = spark.createDataFrame([(w,) for w in WORDS], "w string").select("w", F.soundex("w").alias("c")).collect()
    assert [r.c for r in rows] == [language.Soundex().encode(r.w) for r in rows]
    meta = language.Metaphone()
    assert [(w, phonetic.metaphone(w)) for w in WORDS] == [(w, meta.metaphone(w)) for w in WORDS]


def test_double_metaphone(spark):
    rng = random.Random(7)
    parts = "a e i o u y b c d f g h j k l m n p q r s t v w x z ch cc sch gh gn th tio cia dg ll umb zz wicz sh ps kn wr ie er ai".split()
    words = WORDS + ["".join(rng.choices(parts, k=rng.randrange(1, 8))) for _ in range(1500)]
    encoder = spark._jvm.org.apache.commons.codec.language.DoubleMetaphone()
    both = [(w, (encoder.doubleMetaphone(w, False).strip(), encoder.doubleMetaphone(w, True))) for w in words]
    assert [(w, phonetic.double_metaphone(w)) for w in words] == both


def test_odd_values_give_no_code(spark):
    values = [["", "1st", "x9", "é ß", "a"], None, []]
    df = spark.createDataFrame([(v,) for v in values], "v array<string>")
    for name in (*ENCODERS, "soundex"):
        rows = [r[0] for r in df.select(REGISTRY[name].of_values(F.col("v"))).collect()]
        assert rows[1] == rows[2] == [] and all(c for c in rows[0])
