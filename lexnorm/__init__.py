"""lexnorm: lexical normalization of very large text collections on Spark."""

__version__ = "0.1.0"
