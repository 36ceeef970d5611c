"""biascut: estimating maximum directed cuts from bias snapshots, natively on Spark."""
