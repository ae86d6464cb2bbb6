"""geohist: private location histograms and corpus operators on Spark."""
