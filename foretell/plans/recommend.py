"""Recommendation: a number that a user's and an item's identifier predict, by matrix factorisation.

The factors are two tables; scoring joins them, and their product is an ordinary expression.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tasks import split_of


@dataclass
class Recommender:
    """Factors by identifier, the mean for pairs that training has not seen, and the root mean squared
    validation error of both."""

    user: str
    item: str
    users: DataFrame
    items: DataFrame
    mean: float
    valid_error: float
    mean_error: float

    @classmethod
    def fit(cls, ratings: DataFrame, target: str, predictors: list[str], *, rank: int = 4, iterations: int = 5, l2: float = 0.1, seed: int = 0) -> Recommender:
        from pyspark.ml.recommendation import ALS

        user, item = predictors
        rows = ratings.select(F.col(user).cast("int").alias("user"), F.col(item).cast("int").alias("item"), F.col(target).cast("float").alias("rating")).dropna()
        rows = rows.groupBy("user", "item").agg(F.avg("rating").alias("rating"))
        rows = rows.withColumn("split", split_of(F.concat_ws("|", "user", "item"), seed))
        train = rows.filter("split = 'train'")
        mean = float(train.agg(F.avg("rating")).first()[0] or 0.0)
        # what is left of the mean is factorised, so an unseen pair has the mean
        model = ALS(userCol="user", itemCol="item", ratingCol="left", rank=rank, maxIter=iterations, regParam=l2, seed=seed).fit(train.withColumn("left", F.col("rating") - mean))
        out = cls(user, item, model.userFactors, model.itemFactors, mean, 0.0, 0.0)
        scored = out.score(rows.filter("split = 'valid'").withColumnsRenamed({"user": user, "item": item}), "_p")
        errors = scored.agg(F.sqrt(F.avg(F.pow(F.col("_p") - F.col("rating"), 2))).alias("e"), F.sqrt(F.avg(F.pow(F.lit(mean) - F.col("rating"), 2))).alias("m")).first()
        out.valid_error, out.mean_error = float(errors["e"] or 0.0), float(errors["m"] or 0.0)
        return out

    def score(self, df: DataFrame, name: str) -> DataFrame:
        """``df`` with the predicted number."""
        users = self.users.select(F.col("id").alias("_user"), F.col("features").alias("_u"))
        items = self.items.select(F.col("id").alias("_item"), F.col("features").alias("_v"))
        joined = df.join(users, F.col(self.user) == F.col("_user"), "left").join(items, F.col(self.item) == F.col("_item"), "left")
        product = F.aggregate(F.zip_with("_u", "_v", lambda a, b: (a * b).cast("double")), F.lit(0.0), lambda a, x: a + x)
        return joined.withColumn(name, F.lit(self.mean) + F.coalesce(product, F.lit(0.0))).drop("_user", "_u", "_item", "_v")
