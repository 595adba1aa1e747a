"""coarsesample: approximate aggregation over weighted samples of whole partitions, on PySpark."""
