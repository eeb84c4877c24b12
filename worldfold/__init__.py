"""worldfold: possible-worlds private analytics and corpus operators on PySpark."""
