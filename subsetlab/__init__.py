"""Training-subset selection on Spark: entropy pruning, reference-guided clustering, budgeted scene sampling."""
