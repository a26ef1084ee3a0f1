"""All registered queries outside the training-data operators: name -> (function, SQL or None)."""

from ordsum.workloads import apps, maps, surrounding

ALL = {**maps.Q, **apps.Q, **surrounding.Q}
