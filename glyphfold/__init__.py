"""glyphfold: lossless summaries of labelled, directed, weighted graphs on Spark."""

__version__ = "0.1.0"
