"""Block-bundled rank and sparse products on link graphs, as Spark DataFrame plans."""
