"""corpuskit: a PySpark engine that builds, cleans, audits and releases text corpora."""

__version__ = "0.1.0"
