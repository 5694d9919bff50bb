"""Figures of sf0.01 that were computed once with other tools."""

import pytest
from pyspark.sql import functions as F

import paramstore.queries  # noqa: F401
from paramstore.operators import codecs
from paramstore.registry import QUERIES
from paramstore.sources import zoo

SF = "/root/testdata/sf0.01"


def test_encoders_on_all_models(spark):
    de = QUERIES["de_practical"](spark, SF).agg(F.sum("original"), F.sum("compressed")).first()
    assert tuple(de) == (18_080_000, 8_451_932)
    unit = QUERIES["unit_sizes"](spark, SF).agg(F.sum("compressed")).first()
    assert unit[0] == 21_184_346


def test_pooled_embeddings(spark):
    pooled = zoo.params(spark, SF, ("vec",)).withColumns({"pos": F.substring_index("layer_id", ".", -1).cast("long") * 64 + F.col("layer_pos"), "model_id": F.lit("all")})
    assert codecs.chimp(pooled).first().compressed == 1_068_772
    assert codecs.lorenzo(pooled.drop("bits")).select((F.col("coded") / F.col("params")).alias("s")).first().s == pytest.approx(0.0155, abs=2e-4)


def test_document_layers(spark):
    r = QUERIES["layer_dedup"](spark, SF).first()
    assert (r.units, r.distinct_units, r["bytes"], r.removable, r.member) == (1000, 927, 2_472_458, 163_961, 313_312)
    r = QUERIES["fsc_512"](spark, SF).first()
    assert (r.units, r.distinct_units, r.removable, r.member) == (5337, 4964, 170_181, 324_685)
    assert QUERIES["similar_layer"](spark, SF).first().similar == 164_041
