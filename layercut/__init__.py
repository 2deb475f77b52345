"""layercut: sparse layered networks, partitioned by rows, on PySpark."""
