"""Distribution sorting for Spark: sampled splitters, counted buckets, one planned exchange a level."""
