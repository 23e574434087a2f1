"""Unbiased, level-sampled vector compression on Spark.

``sources``: schemas, readers, sinks. ``functions``: hashed uniforms, SQL functions, bit packing. ``operators``: vectors, compressors, ladders of levels,
level probabilities, estimators, costs, accuracy. ``plans``: losses, training loops, theory, workloads, registered queries. ``streaming``: online training.
"""
