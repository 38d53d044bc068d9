"""rankgrid: products of large block matrices as Spark plans."""

__version__ = "0.1.0"
