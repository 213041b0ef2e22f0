"""packvec: hybrid nearest-neighbour search on Spark with segment-packed scalar quantization."""

__version__ = "0.1.0"
