"""cfengine: collaborative filtering on implicit feedback, written for Spark.

Subpackages: ``sources`` (feedback tables), ``functions`` (column maths),
``operators`` (samplers, gradients, trainers, measures), ``plans`` (planner and
plan checks), ``streaming`` (event streams). ``llm`` holds the training-data
operators; nothing else in the package imports it.
"""
