"""Multi-manifold streaming embedding on Spark, with corpus operators beside it."""
