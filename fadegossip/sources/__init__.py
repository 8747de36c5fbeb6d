"""Tables, canonical item streams and generated streams."""

from fadegossip.sources.streams import FIXTURES, Fixture, canonical, fingerprint, stream
from fadegossip.sources.tables import read_table
from fadegossip.sources.zipf import ZipfSource, zipf_cdf, zipf_stream

__all__ = ["FIXTURES", "Fixture", "ZipfSource", "canonical", "fingerprint", "read_table", "stream", "zipf_cdf", "zipf_stream"]
