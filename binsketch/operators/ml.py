"""A pipeline stage: an array of elements in, the expanded sparse vector of its coded sketch out."""

from __future__ import annotations

from pyspark import keyword_only
from pyspark.ml import Transformer
from pyspark.ml.feature import CountVectorizerModel, Normalizer
from pyspark.ml.param import Param, Params, TypeConverters
from pyspark.ml.param.shared import HasInputCol, HasOutputCol
from pyspark.ml.util import DefaultParamsReadable, DefaultParamsWritable
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class BinMinTransformer(Transformer, HasInputCol, HasOutputCol, DefaultParamsReadable, DefaultParamsWritable):
    """Row-local: permute, bin, minimum, b low bits, blank coding, unit length. Parameters are saved with the pipeline."""

    k = Param(Params._dummy(), "k", "bins", typeConverter=TypeConverters.toInt)
    b = Param(Params._dummy(), "b", "bits of a code", typeConverter=TypeConverters.toInt)
    size = Param(Params._dummy(), "size", "universe size, a multiple of k", typeConverter=TypeConverters.toInt)
    a = Param(Params._dummy(), "a", "the permutation's factor, prime to size", typeConverter=TypeConverters.toInt)
    shift = Param(Params._dummy(), "shift", "the permutation's offset", typeConverter=TypeConverters.toInt)

    @keyword_only
    def __init__(self, *, inputCol=None, outputCol=None, k=256, b=8, size=1 << 24, a=1140671485, shift=12820163):
        super().__init__()
        self._setDefault(k=256, b=8, size=1 << 24, a=1140671485, shift=12820163)
        self._set(**{n: v for n, v in self._input_kwargs.items() if v is not None})

    def _transform(self, dataset: DataFrame) -> DataFrame:
        k, b, size, a, shift = (self.getOrDefault(p) for p in (self.k, self.b, self.size, self.a, self.shift))
        width = size // k

        pos = F.transform(F.coalesce(F.col(self.getInputCol()), F.array().cast("array<bigint>")), lambda e: (e * F.lit(a) + F.lit(shift)) % F.lit(size))
        least = F.aggregate(F.array_sort(pos), F.array().cast("array<bigint>"), lambda acc, p: F.when((F.size(acc) > 0) & (F.floor(F.try_element_at(acc, F.lit(-1)) / F.lit(width)) == F.floor(p / F.lit(width))), acc).otherwise(F.concat(acc, F.array(p))))
        index = F.transform(least, lambda p: (F.floor(p / F.lit(width)) * F.lit(1 << b) + F.lit((1 << b) - 1) - (p % F.lit(width)).bitwiseAND(F.lit((1 << b) - 1))).cast("int"))
        out = self.getOutputCol()
        names, counts = (next(f"{out}_{w}{'_' * n}" for n in range(9) if f"{out}_{w}{'_' * n}" not in dataset.columns) for w in ("names", "counts"))
        model = CountVectorizerModel.from_vocabulary([str(i) for i in range(k << b)], names, counts)  # each name once: ones
        coded = model.transform(dataset.withColumn(names, index.cast("array<string>")))
        return Normalizer(p=2.0, inputCol=counts, outputCol=out).transform(coded).drop(names, counts)
