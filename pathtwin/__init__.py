"""Clone detection over flow-graph paths, expressed as Spark plans."""
