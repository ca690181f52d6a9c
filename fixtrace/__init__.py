"""fixtrace: which released versions carry a known vulnerability, computed on Spark."""
