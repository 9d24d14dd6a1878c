"""Row types of the model tables, in one place."""

from __future__ import annotations

SOURCE = "app_id string, version int, path string, content string, sha string, lang string"
STEP = "struct<name:string,kind:string>"
STEPS = f"array<{STEP}>"
#: What the front end makes of one file: nested here, flat in the bundle's tables.
MODEL = (
    "app_id string, version int, path string, error string, "
    "units array<struct<unit:int,parent:int,kind:string,name:string,call_seq:int,params:array<string>>>, "
    "elements array<struct<elem:int,parent:int,unit:int,block:int,ord:int,kind:string,name:string,literal:string,literal_type:string,line_from:int,line_to:int,text:string>>, "
    "nodes array<struct<seq:int,unit:int,block:int,elem:int,kind:string,branch:array<string>,loops:array<int>,line:int,text:string>>, "
    f"uses array<struct<seq:int,elem:int,block:int,root:string,steps:{STEPS},role:string,literal_type:string>>, "
    f"aliases array<struct<seq:int,lhs:string,root:string,steps:{STEPS}>>, "
    "calls array<struct<seq:int,unit:int,chain:int,pos:int,name:string,n_chain:int,container:string,container_var:string,receiver:string,result:string,result_seq:int,element:boolean,callback:int,text:string>>, "
    f"args array<struct<seq:int,arg:int,key:string,root:string,steps:{STEPS},literal:string,literal_type:string>>, "
    "resolved array<struct<seq:int,callee:string>>"
)
TABLES = ("units", "elements", "nodes", "uses", "aliases", "calls", "args", "resolved")
#: Dictionary of the store's calls: call name, kind, argument with the filter, argument with the payload, many results.
API = "call string, kind string, filter_arg int, payload_arg int, multi boolean, scalar boolean"
