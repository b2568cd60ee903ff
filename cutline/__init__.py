"""cutline: balanced cuts, dissection orders and contraction indexes of large geometric graphs on Spark."""
