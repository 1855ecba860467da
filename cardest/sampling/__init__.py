"""Building, storing and maintaining the sample of a database."""

from cardest.sampling.build import SampleDB, create_sample, create_sample_for

__all__ = ["SampleDB", "create_sample", "create_sample_for"]
