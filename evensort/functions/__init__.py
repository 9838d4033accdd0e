"""Column functions: key codecs, integer mixing, partition lookup, registered UDFs."""
