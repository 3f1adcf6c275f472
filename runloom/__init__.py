"""runloom: dictionary matching on run-length encoded sequences, as Spark plans."""
