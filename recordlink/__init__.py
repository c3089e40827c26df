"""Record linkage for Spark: serialize, encode, gather, verify, select, tag."""
