"""binflow: partition-granular graph programs and corpus operators on PySpark DataFrames."""
