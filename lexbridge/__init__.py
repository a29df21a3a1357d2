"""A Spark-native engine for adapting text classifiers across domains through shared words."""

import os


def reach(spark) -> None:
    """Lets Python workers import this package from where the driver has it, wherever the driver was started.

    A cluster whose executors do not see that folder gets the package by ``--py-files`` as usual.
    """
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    env = spark.sparkContext.environment
    paths = [p for p in env.get("PYTHONPATH", "").split(os.pathsep) if p]
    if root not in paths:
        env["PYTHONPATH"] = os.pathsep.join([root, *paths])
