"""sitereach: a Spark-native engine for choosing places whose audience carries word of mouth furthest."""
