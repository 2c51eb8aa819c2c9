"""trilist.sources"""
