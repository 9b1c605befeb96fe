"""skewmap: skew-aware static key->value indexes as Spark tables.

Sub-packages
------------
``functions``  closed-form cost curves and bounds (Column and float forms)
``plans``      deciding whether, and how, to gate an index
``operators``  profiles, prefix codes, retrieval structures, gates, baselines, measures
``sources``    table readers, index storage, the Python data source, generators
``streaming``  drift windows, replanning, base-plus-delta lookups
"""

__version__ = "0.1.0"
