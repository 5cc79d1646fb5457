"""vecgraph: graph-aware learned vector quantization and graph search on PySpark."""
