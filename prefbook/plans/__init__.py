"""Choice of the execution strategy, and the engines behind it."""
