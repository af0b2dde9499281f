"""cutstream: buffered multilevel partitioning of vertex streams on Spark."""
