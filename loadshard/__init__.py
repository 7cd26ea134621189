"""PySpark-native analytics over triples with workload-aware fragmentation."""
