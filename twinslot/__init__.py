"""twinslot: set intersection and pair mining at scale on Spark DataFrames."""

__version__ = "0.1.0"
