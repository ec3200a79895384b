"""Regular path queries over grammar-generated provenance runs, on Spark."""

__version__ = "0.1.0"
