"""pullgraph: tile-based pull-model graph analytics on PySpark."""

__version__ = "0.1.0"
