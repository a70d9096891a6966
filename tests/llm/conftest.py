import sys

sys.path.insert(0, __file__.rsplit("/tests/", 1)[0])
