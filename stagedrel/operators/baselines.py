"""Closed-head classifiers: stand-ins for a family of models with a fixed classification layer, told apart by what they see."""

from __future__ import annotations

from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import StringIndexer
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Columns of the feature array by view: image 0-15, crop 16-19, text 20-35.
IMAGE, CROP, TEXT = (0, 16), (16, 4), (20, 16)
VIEWS = {
    "closed_text": [TEXT], "closed_image": [IMAGE], "closed_crop": [CROP], "closed_image_crop": [IMAGE, CROP],
    "closed_text_image": [TEXT, IMAGE], "closed_all": [TEXT, IMAGE, CROP], "closed_all_cross": [TEXT, IMAGE, CROP],
}


def _view(name: str):
    x = F.concat(*[F.slice("x", at + 1, n) for at, n in VIEWS[name]])
    if name.endswith("_cross"):
        crop, text = F.slice("x", CROP[0] + 1, CROP[1]), F.slice("x", TEXT[0] + 1, TEXT[1])
        x = F.concat(x, F.flatten(F.transform(crop, lambda c: F.transform(text, lambda t: c * t))))
    return array_to_vector(x)


def closed_head(train: DataFrame, test: DataFrame, view: str = "closed_all", iterations: int = 20) -> DataFrame:
    """(sample_id, gold, pred): one multinomial layer over the labels seen in training, and no others."""
    index = StringIndexer(inputCol="gold", outputCol="y", handleInvalid="keep", stringOrderType="alphabetAsc").fit(train)
    seen = list(index.labels)
    data = index.transform(train).select("y", _view(view).alias("features"))
    model = LogisticRegression(labelCol="y", maxIter=iterations, regParam=1e-3, family="multinomial").fit(data)
    out = model.transform(test.select("sample_id", "gold", _view(view).alias("features")))
    return out.select("sample_id", "gold", F.coalesce(F.get(F.array(*[F.lit(s) for s in seen]), F.col("prediction").cast("int")), F.lit(seen[0])).alias("pred"))
