"""Communication-minimal re-layout of distributed matrices and tables on Spark."""
