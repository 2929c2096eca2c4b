"""Which rows the language profiles are learned from."""

from collections import Counter

from pyspark.sql import functions as F

from bucketcsr.llm import langid


def test_every_language_keeps_training_rows_and_their_number_stays_bounded(spark):
    # eight languages of one text each, 1,000 copies with ids of their own; one of a single row repeated 1,000 times
    words = ["uno dos", "eins zwei", "one two", "un deux", "yksi kaksi", "jeden dwa", "bir iki", "satu dua", "egy ketto"]
    texts = F.array(*[F.lit(w) for w in words])
    docs = spark.range(9000).select(F.when(F.col("id") % 9 == 8, 8).otherwise(F.col("id")).alias("doc_id"), F.element_at(texts, (F.col("id") % 9 + 1).cast("int")).alias("text"), F.concat(F.lit("l"), F.col("id") % 9).alias("lang"))
    spec = langid.Hyper(sample=50)
    names, prototypes = langid.learn(docs, spec=spec)
    assert names == [f"l{k}" for k in range(9)] and prototypes.shape == (9, spec.width)
    drawn = Counter(r["l"] for r in langid.draw(docs, doc_id="doc_id", spec=spec).collect())
    assert drawn["l8"] == 1 and all(20 < drawn[f"l{k}"] < 100 for k in range(8))
